"""The given tables, and the four carriers of ranked beams over them.

A beam item has beam_id, pos (1 is the best rank), item_id, correct, verified and score. Texts stay in
their tables and are joined back by identifier at the end.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

TABLES = [
    "region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events",
    "documents", "embeddings", "pages", "benchmark", "labels", "conversations",
]

#: Columns of the tables, in order.
COLUMNS = {
    "region": "r_regionkey r_name", "nation": "n_nationkey n_name n_regionkey",
    "customer": "c_custkey c_name c_nationkey c_acctbal c_mktsegment", "supplier": "s_suppkey s_name s_nationkey s_acctbal",
    "part": "p_partkey p_name p_brand p_type p_size p_retailprice",
    "orders": "o_orderkey o_custkey o_orderstatus o_totalprice o_orderdate o_orderpriority",
    "lineitem": "l_orderkey l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate",
    "events": "event_id ts user_id event_type value props", "documents": "doc_id text lang source n_chars",
    "embeddings": "vec_id embedding label", "pages": "page_id url html", "benchmark": "item_id text",
    "labels": "doc_id quality toxic", "conversations": "conv_id turn role text",
}

#: Foreign keys of the tables: (table, column) -> (table, column).
FOREIGN_KEYS = {
    ("nation", "n_regionkey"): ("region", "r_regionkey"),
    ("customer", "c_nationkey"): ("nation", "n_nationkey"),
    ("supplier", "s_nationkey"): ("nation", "n_nationkey"),
    ("orders", "o_custkey"): ("customer", "c_custkey"),
    ("lineitem", "l_orderkey"): ("orders", "o_orderkey"),
    ("lineitem", "l_partkey"): ("part", "p_partkey"),
    ("lineitem", "l_suppkey"): ("supplier", "s_suppkey"),
    ("labels", "doc_id"): ("documents", "doc_id"),
}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def schema_columns(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """table_name, column_name, ordinal, is_key, fk_table and fk_column, from the files' schemas."""
    rows = []
    for t in names or TABLES:
        for i, c in enumerate(table(spark, sf_dir, t).columns, 1):
            to = FOREIGN_KEYS.get((t, c))
            rows.append((t, c, i, to is not None or (t, c) in FOREIGN_KEYS.values(), *(to or (None, None))))
    return spark.createDataFrame(rows, "table_name string, column_name string, ordinal int, is_key boolean, fk_table string, fk_column string")


#: Order of the items of a line beam: total, as the five columns together are unique.
LINE_ORDER = ["l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]


def line_beams(spark: SparkSession, sf_dir: str, extra: list[str] | None = None) -> DataFrame:
    # the beam is named before ranks are taken, so that later aggregates by beam reuse the exchange
    lines = table(spark, sf_dir, "lineitem").withColumnRenamed("l_orderkey", "beam_id")
    ranked = lines.withColumn("pos", F.row_number().over(Window.partitionBy("beam_id").orderBy(*LINE_ORDER)))
    return ranked.select(
        "beam_id",
        "pos",
        (F.col("beam_id") * 1000 + F.col("pos")).alias("item_id"),
        (F.col("l_returnflag") == "R").alias("correct"),
        (F.col("l_discount") <= 0.05).alias("verified"),
        F.col("l_quantity").alias("score"),
        F.col("l_extendedprice").alias("price"),
        *(extra or []),
    )


LINE_SQL = """line_beams as (
  select l_orderkey as beam_id, pos, l_orderkey * 1000 + pos as item_id, l_returnflag = 'R' as correct,
         l_discount <= 0.05 as verified, l_quantity as score, l_extendedprice as price
  from (select *, row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice)::int as pos
        from lineitem))"""


def words(text: Column) -> Column:
    """Distinct lower-case pieces between single spaces."""
    return F.array_distinct(F.split(F.lower(text), " "))


def chat_beams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Assistant turns as candidates for the first question of a conversation."""
    turns = table(spark, sf_dir, "conversations").withColumnRenamed("conv_id", "beam_id")
    asked = turns.where("role = 'user'").groupBy("beam_id").agg(F.min_by("text", "turn").alias("question"))
    rank = Window.partitionBy("beam_id").orderBy("turn")
    items = turns.where("role = 'assistant'").join(asked, "beam_id")
    overlap = F.size(F.array_intersect(words(F.col("question")), words(F.col("text"))))
    return items.select(
        "beam_id",
        F.row_number().over(rank).alias("pos"),
        (F.col("beam_id") * 1000 + F.row_number().over(rank)).alias("item_id"),
        (F.size(F.split("text", " ")) >= F.size(F.split("question", " "))).alias("correct"),
        (overlap * 5 >= F.size(words(F.col("question")))).alias("verified"),
        overlap.cast("double").alias("score"),
        "question",
        "text",
    )


CHAT_SQL = """chat_beams as (
  select conv_id as beam_id, pos, conv_id * 1000 + pos as item_id,
         len(string_split(text, ' ')) >= len(string_split(question, ' ')) as correct,
         5 * overlap >= len(list_distinct(string_split(lower(question), ' '))) as verified, overlap::double as score, question, text
  from (select c.conv_id, c.text, q.question, row_number() over (partition by c.conv_id order by c.turn)::int as pos,
               len(list_intersect(list_distinct(string_split(lower(q.question), ' ')), list_distinct(string_split(lower(c.text), ' ')))) as overlap
        from conversations c join (select conv_id, arg_min(text, turn) as question from conversations where role = 'user' group by conv_id) q using (conv_id)
        where c.role = 'assistant'))"""


#: Identifiers in a run that one task puts in order.
RUN = 100_000


def doc_beams(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents of a source and language as candidates, in order of their identifiers.

    A source may hold a third of all documents: ranks are taken within runs of identifiers, and
    counts of the runs before are added, so that no task sorts a whole group.
    """
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    own = docs.select("source", "lang", "doc_id", "n_chars", F.expr(f"doc_id div {RUN}").alias("run"))
    before = Window.partitionBy("source", "lang").orderBy("run").rowsBetween(Window.unboundedPreceding, -1)
    starts = own.groupBy("source", "lang", "run").count().select("source", "lang", "run", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("first"))
    inside = own.withColumn("place", F.row_number().over(Window.partitionBy("source", "lang", "run").orderBy("doc_id")))
    same = [inside[c].eqNullSafe(starts[c]) for c in ("source", "lang", "run")]
    ranked = inside.join(starts, same).select(inside["source"], inside["lang"], "doc_id", "n_chars", (F.col("place") + F.col("first")).cast("int").alias("pos"))
    joined = ranked.join(labels, "doc_id", "left")
    return joined.select(F.concat_ws("/", "source", "lang").alias("beam_id"), "pos", F.col("doc_id").alias("item_id"), (F.col("quality") == 1).alias("correct"), F.col("n_chars").cast("double").alias("score"))


DOC_SQL = """doc_beams as (
  select d.source || '/' || d.lang as beam_id, row_number() over (partition by d.source, d.lang order by d.doc_id)::int as pos,
         d.doc_id as item_id, l.quality = 1 as correct, d.n_chars::double as score
  from documents d left join labels l using (doc_id))"""


def from_rows(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    """A beam table from any generator's output: (beam_id, pos, item_id, correct, verified, score)."""
    return spark.createDataFrame(rows, "beam_id bigint, pos int, item_id bigint, correct boolean, verified boolean, score double")


def beam_table(df: DataFrame) -> DataFrame:
    """``df`` if it has the columns of a beam table; any generator may have made it."""
    missing = {"beam_id", "pos", "item_id"} - set(df.columns)
    if missing:
        raise ValueError(f"not a beam table: no {sorted(missing)}")
    return df
