"""Queries of the corpus operators and the SQL that states their results."""

from __future__ import annotations

from beamrank.llm.exact_dedup import exact_groups
from beamrank.llm.licenses import RULES, SENTENCES, STEMS, scan_licenses
from beamrank.llm.mixing import mix_counts
from beamrank.llm.near_dedup import near_classes
from beamrank.llm.ngrams import score_documents as score_by_language_model
from beamrank.llm.packing import pack_documents
from beamrank.llm.quality import score_documents
from beamrank.llm.sharding import shard_documents
from beamrank.llm.sstable import encode_to_tables
from beamrank.llm.vectors import vector_links


def _table(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_best_fit_packing(spark, sf_dir):
    return pack_documents(_table(spark, sf_dir, "documents"))


def op2_license_scan(spark, sf_dir):
    return scan_licenses(_table(spark, sf_dir, "documents"))


def op3_histogram_sort(spark, sf_dir):
    return shard_documents(_table(spark, sf_dir, "documents"))


def op4_bag_minhash(spark, sf_dir):
    return near_classes(_table(spark, sf_dir, "documents"))


#: The least order with a level of each kind, whatever disk it takes; figures are in the README.
LM_ORDER = 3


def op5_kneser_ney(spark, sf_dir):
    return score_by_language_model(_table(spark, sf_dir, "documents"), LM_ORDER)


def op6_mix_sources(spark, sf_dir):
    from pyspark.sql import functions as F

    out = mix_counts(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).alias("taken"))


def op7_collision_counting(spark, sf_dir):
    return vector_links(_table(spark, sf_dir, "embeddings"))


def op8_quality_classifier(spark, sf_dir):
    return score_documents(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


def op9_sorted_tables(spark, sf_dir):
    return encode_to_tables(spark, _table(spark, sf_dir, "documents"))


def op10_exact_dedup(spark, sf_dir):
    return exact_groups(_table(spark, sf_dir, "documents"))


def queries():
    return {
        "op1_best_fit_packing": op1_best_fit_packing,
        "op2_license_scan": op2_license_scan,
        "op3_histogram_sort": op3_histogram_sort,
        "op4_bag_minhash": op4_bag_minhash,
        "op5_kneser_ney": op5_kneser_ney,
        "op6_mix_sources": op6_mix_sources,
        "op7_collision_counting": op7_collision_counting,
        "op8_quality_classifier": op8_quality_classifier,
        "op9_sorted_tables": op9_sorted_tables,
        "op10_exact_dedup": op10_exact_dedup,
    }


OP2_SQL = """
with known as (select unnest([{keys}]) as id, unnest([{texts}]) as sentence),
rules as (select unnest([{rules}]) as rule, unnest([{licenses}]) as license, unnest([{patterns}]) as pattern),
d as (select row_number() over () as r, doc_id, text from documents where regexp_matches(lower(text), '{stems}')),
cut as (
  select r, doc_id, unnest(string_split_regex(regexp_replace(text, '([.!?])[ \t\r\f]+', '\1' || chr(10), 'g'), '\n+')) as s,
         unnest(range(0, len(string_split_regex(regexp_replace(text, '([.!?])[ \t\r\f]+', '\1' || chr(10), 'g'), '\n+')))) as nth
  from d),
seen as (
  select r, doc_id, nth, id from cut join known on trim(regexp_replace(lower(s), '[^a-z0-9]+', ' ', 'g')) = sentence),
docs as (select r, any_value(doc_id) as doc_id, string_agg('<' || id || '@' || nth || '>', '' order by nth) as sequence from seen group by r),
spans as (select r, doc_id, unnest(regexp_extract_all(sequence, '{either}')) as span from docs)
select doc_id, license, rule, count(*)::bigint as matches, min(regexp_extract(span, '@([0-9]+)', 1)::int) as first_sentence
from spans join rules on regexp_replace(span, '@[0-9]+', '', 'g') = pattern group by r, doc_id, license, rule
""".format(
    keys=", ".join(map(str, SENTENCES)),
    texts=", ".join(f"'{s}'" for s in SENTENCES.values()),
    rules=", ".join(f"'{r[0]}'" for r in RULES),
    licenses=", ".join(f"'{r[1]}'" for r in RULES),
    patterns=", ".join("'" + "".join(f"<{i}>" for i in r[2]) + "'" for r in RULES),
    stems="|".join(STEMS),
    either="|".join("".join(f"<{i}@[0-9]+>" for i in ids) for ids in sorted((r[2] for r in RULES), key=len, reverse=True)),
)

#: CRC-32 of the UTF-8 bytes of t in table ``source``, from the rule of its polynomial.
CRC_SQL = """
crc_table as (
  select list(list_reduce(list_prepend(i, range(8)), lambda c, n: case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end) order by i) as tab
  from (select unnest(range(256)) as i)),
crc as (
  select {key}, xor(list_reduce(list_prepend(4294967295::bigint,
           list_transform(regexp_extract_all(hex(encode({text})), '..'), lambda h: ('0x' || h)::bigint)),
           lambda c, b: xor(c >> 8, tab[(xor(c, b) & 255) + 1])), 4294967295) as value
  from {source}, crc_table)"""

OP3_SQL = """
with d as (
  select doc_id, strlen(coalesce(text, '')) + 16 as size, coalesce(text, '') as t,
         ('0x' || substr(md5(coalesce(text, '')), 1, 10))::bigint * 1048576
           + ('0x' || substr(md5(coalesce(doc_id::varchar, '')), 1, 5))::bigint as key
  from documents),
keys as (select key, key >> 20 as grp, sum(size)::bigint as bytes from d group by key),
cuts as (
  select key, below from (
    select key, coalesce(sum(bytes) over (order by key rows between unbounded preceding and 1 preceding), 0)::bigint as below,
           lag(grp) over (order by key) is distinct from grp as first, sum(bytes) over (partition by grp) as group_bytes from keys)
  where first or group_bytes * 40 > (select sum(size) from d)
  union all select 1152921504606846976, (select sum(size) from d)::bigint),
splitters as (
  select j, arg_min(key, (abs(40 * below - (select sum(size) from d) * j)::hugeint * 2000000000000000000 + key)) as cut
  from cuts, (select unnest(range(1, 40)) as j) group by j),
placed as (
  select doc_id, size, t, key, (select count(*) from splitters where cut <= key)::int as shard from d),
texts as (select distinct t from d),
""" + CRC_SQL.format(key="t", text="t", source="texts") + """
select doc_id, size::bigint as size, value as text_crc32, 'bytes' as law, shard,
       (row_number() over (partition by shard order by key, doc_id) - 1)::bigint as slot,
       null::int as grown_shard
from placed join crc using (t)
"""

OP6_SQL = r"""
with d as (
  select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents),
s as (
  select source, sum(size)::bigint as source_size,
         (case (row_number() over (order by source nulls last) - 1) % 3 when 0 then 5.0 when 1 then 2.0 else 1.0 end)::double as weight
  from d group by source),
l as (
  select *, ((sum(source_size) over () - 3 * coalesce(sum(source_size) over (order by source_size / weight, source nulls last rows between unbounded preceding and 1 preceding), 0))
     / sum(weight) over (order by source_size / weight, source nulls last rows between current row and unbounded following))::double as level from s),
t as (
  select *, coalesce(least(3.0::double * source_size, (max(level) filter (level * weight <= 3 * source_size) over ()) * weight), 0)::double as target from l),
r as (select *, case when source_size > 0 then least(3.0::double, target / source_size) else 0.0 end as rate from t),
u as (
  select d.doc_id, d.size, r.source, r.source_size, r.target, r.rate, k,
         ('0x' || substr(md5(coalesce(d.doc_id::varchar, '') || ':' || (k // 4)::varchar), (8 * (k % 4) + 1)::int, 8))::bigint / 4294967296.0::double as draw
  from d join r on d.source is not distinct from r.source, (select unnest(range(0, 16)) as k)),
m as (
  select source, k, abs(floor(any_value(rate)) * any_value(source_size) + sum(case when draw < rate - floor(rate) then size else 0 end) - any_value(target)) as miss
  from u group by source, k),
c as (select source, arg_min(k, (miss, k)) as seed from m group by source)
select doc_id, size, source_size, target,
       ((floor(rate) + case when draw < rate - floor(rate) then 1 else 0 end) * size)::bigint as taken
from u join c on u.source is not distinct from c.source and u.k = c.seed
"""

OP7_SQL = """
with recursive e as (
  select vec_id, label, embedding::double[] as v from embeddings
  where label is not null and embedding is not null
    and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
links as (
  select a.vec_id as a, b.vec_id as b from e a join e b on a.label = b.label and a.vec_id <> b.vec_id
  where list_cosine_similarity(a.v, b.v) >= 0.93),
reach as (select vec_id as a, vec_id as b from embeddings union select r.a, l.b from reach r join links l on r.b = l.a),
least as (select a, min(b) as component_id from reach group by a),
n as (select a, count(*) as n_links from links group by a)
select vec_id, coalesce(n_links, 0)::bigint as n_links, component_id, vec_id = component_id as kept
from embeddings join least on vec_id = least.a left join n on vec_id = n.a
"""

OP10_SQL = """
select doc_id, max(doc_id) over g as keep_id, count(*) over g as group_size,
       row_number() over (partition by coalesce(text, '') order by doc_id desc nulls last) = 1 as kept, sha256(coalesce(text, '')) as text_sha256
from documents window g as (partition by coalesce(text, ''))
"""


def oracle_sql():
    return {"op2_license_scan": OP2_SQL, "op3_histogram_sort": OP3_SQL, "op6_mix_sources": OP6_SQL, "op7_collision_counting": OP7_SQL, "op10_exact_dedup": OP10_SQL}
