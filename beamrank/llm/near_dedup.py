"""Near-duplicate classes of texts by BagMinHash, banding and exact verification.

Signatures. A text is the multiset of its runs of ``words`` words (a shorter text: one run of all
its words). The weight axis of a shingle is cut at 1, 2, 4, 8, ...; each interval below or around
its count carries a Poisson process of rate equal to the interval's length, drawn by hash, and a
point counts only if its place on the axis is below the count. All points below a count thus form a
process of that rate, the same for every text, and the least point in each of ``registers`` equals
in two texts with probability equal to their weighted Jaccard similarity. Points are drawn in
ascending order only until no register can change.

Candidates. Texts that agree on all registers of a band are tied in a star around the least of
them; stars join into candidate components. Equal texts are one vertex throughout (their hash), and
are combined before every shuffle.

Verification. The texts of candidate components are compared within components by multiset overlap;
only pairs that are not connected yet are looked at, and pairs whose signatures say less than
``threshold`` by over five standard deviations are passed over. A component of more than ``block``
texts (fewer if they are long) is first compared with its best-connected text, text by text; what that links needs no
comparison among itself, and the rest is compared in pairs of blocks with everything. No pair of
rows is emitted but links, at most one less than a block has texts. Verified links are joined into
classes by contraction.

Edge cases. Null counts as empty. Texts without words are near only to equal texts. Ties and repeated
rows share a class. Null identifiers belong to classes, but name one only if it has no other. An
empty table gives an empty result. Extra columns are not read by ``near_classes`` and pass through
``near_dedup``.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from beamrank.llm import textkit
from beamrank.llm.common import BROADCAST_ROWS, bounded_broadcast, connected_components, durable, text_or_empty

WORDS = 5
THRESHOLD = 0.8
BANDS, ROWS = 25, 5
BLOCK = 256
#: Bytes of text that a block may have, about: blocks of long texts have fewer of them.
BLOCK_BYTES = 4 << 20
#: Narrow enough for the arrays of a slice to stay small.
SLICE_BYTES = 2 << 20

#: Rows that are drawn at once.
_CHUNK = 1 << 20

_C = [np.uint64(0x9E3779B97F4A7C15 * (2 * i + 1) & (1 << 64) - 1) for i in range(16)]


def shingles(column: pa.Array, words: int = WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document, hash and count of each distinct run of words of each text. Words are hashed window by window."""
    hashes, docs = [np.empty(0, np.uint64)], [np.empty(0, np.int32)]
    for first, buf, offsets in textkit.windows(column, textkit.WINDOW_BYTES):
        begin, end, own = textkit.words(buf, offsets)
        hashes.append(textkit.span_hashes(buf, begin, end))
        docs.append((own + first).astype(np.int32))
    h, doc = np.concatenate(hashes), np.concatenate(docs)
    del hashes, docs
    if not len(h):
        return np.empty(0, np.int64), np.empty(0, np.uint64), np.empty(0, np.int64)
    count = np.bincount(doc, minlength=len(column))
    at = np.cumsum(count) - count
    short = []
    for n in range(1, words):
        some = np.flatnonzero(count == n)
        if len(some):
            short.append((textkit.mix64(sum((h[at[some] + i] * _C[i] for i in range(n)), _C[words + n])), some))
    runs = max(0, len(h) - words + 1)
    whole = doc[:runs] == doc[words - 1 :]
    for a in range(0, runs, _CHUNK):
        # a run's hash takes the place of its first word's, which no later run needs
        b = min(runs, a + _CHUNK)
        h[a:b] = textkit.mix64(sum((h[a + i : b + i] * _C[i] for i in range(words)), np.uint64(0)))
    if len(column) == 1 and not short:
        # one long text: no order but that of the hashes is needed
        value = h[:runs]
        value.sort()
        new = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]]))
        return np.zeros(len(new), np.int8), value[new], np.diff(np.append(new, len(value))).astype(np.int32)
    value = np.concatenate([h[:runs][whole], *(v for v, _ in short)])
    owner = np.concatenate([doc[:runs][whole].astype(np.int64), *(o for _, o in short)])
    salted = value ^ textkit.mix64(owner.astype(np.uint64) + _C[1])
    order = np.argsort(salted)
    value, owner, salted = value[order], owner[order], salted[order]
    new = np.flatnonzero(np.concatenate([[True], salted[1:] != salted[:-1]]))
    return owner[new], value[new], np.diff(np.append(new, len(value)))


def bag_minhash(owner: np.ndarray, value: np.ndarray, count: np.ndarray, n: int, registers: int) -> np.ndarray:
    """Signatures (n x registers, 32-bit) of weighted sets given as rows (owner, value, count), so many rows at a time."""
    least = np.full((n, registers), np.inf)
    for a in range(0, len(value), _CHUNK):
        part = slice(a, a + _CHUNK)
        _draw_points(least, owner[part].astype(np.int64), value[part], count[part].astype(np.int64))
    return (textkit.mix64(least.view(np.uint64)) >> np.uint64(32)).astype(np.uint32)


def _draw_points(least: np.ndarray, owner: np.ndarray, value: np.ndarray, count: np.ndarray) -> None:
    """Lower ``least`` by the points of some rows."""
    registers = least.shape[1]
    levels = np.where(count > 1, np.ceil(np.log2(np.maximum(count, 1))).astype(np.int64), 0) + 1
    row = np.repeat(np.arange(len(value)), levels)
    level = np.arange(len(row)) - np.repeat(np.cumsum(levels) - levels, levels)
    owner, weight = owner[row], count[row]
    seed = textkit.mix64(value[row] ^ textkit.mix64((level + 1).astype(np.uint64) * _C[2]))
    rate = np.exp2(np.maximum(level - 1, 0).astype(np.float64))
    time, draw = np.zeros(len(row)), 0
    flat = least.ravel()
    while len(seed):
        r = textkit.mix64(seed + np.uint64((draw + 1) * int(_C[3]) & (1 << 64) - 1))
        time = time - np.log(((r >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / rate
        s = textkit.mix64(r ^ _C[4])
        place = owner * registers + ((s & np.uint64(0xFFFFFFFF)) * np.uint64(registers) >> np.uint64(32)).astype(np.int64)
        inside = (level == 0) | (rate * (1 + (s >> np.uint64(32)).astype(np.float64) * 2.0**-32) < weight)
        np.minimum.at(flat, place[inside], time[inside])
        live = time < least.max(axis=1)[owner]
        if not live.all():
            seed, owner, weight, level, rate, time = (x[live] for x in (seed, owner, weight, level, rate, time))
        draw += 1


def similarity(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Weighted Jaccard similarity of two multisets given as sorted values and counts."""
    (va, ca), (vb, cb) = a, b
    if not len(va) or not len(vb):
        return 0.0
    at = np.minimum(np.searchsorted(va, vb), len(va) - 1)
    both = va[at] == vb
    common = np.minimum(ca[at[both]], cb[both]).sum()
    return common / (ca.sum() + cb.sum() - common)


def _bags(texts: pa.Array, words: int) -> list[tuple[np.ndarray, np.ndarray]]:
    owner, value, count = shingles(texts, words)
    order = np.lexsort((value, owner))
    owner, value, count = owner[order], value[order], count[order]
    cut = np.searchsorted(owner, np.arange(len(texts) + 1))
    return [(value[a:b], count[a:b]) for a, b in zip(cut, cut[1:], strict=False)]


def text_hash():
    """What stands for a text, and all its copies, as a vertex."""
    return F.xxhash64(F.sha2(text_or_empty(), 256))


def signatures(docs: DataFrame, words: int = WORDS, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, h (hash of the text), sig (registers as bytes; null for texts without words) of every document."""
    registers = bands * rows

    def run(batches):
        for batch in batches:
            for part in textkit.slices(batch, "text", SLICE_BYTES):
                owner, value, count = shingles(part.column(2), words)
                sig = bag_minhash(owner, value, count, len(part), registers)
                there = np.bincount(owner, minlength=len(part)) > 0
                raw = [s.tobytes() if t else None for s, t in zip(sig, there, strict=True)]
                yield pa.record_batch([part.column(0), part.column(1), pa.array(raw, pa.binary())], ["doc_id", "h", "sig"])

    keyed = docs.select("doc_id", text_hash().alias("h"), text_or_empty().alias("text"))
    return keyed.mapInArrow(run, "doc_id bigint, h bigint, sig binary")


def _band_keys(signed: DataFrame, bands: int, rows: int) -> DataFrame:
    pieces = [F.xxhash64(F.lit(b), F.substring("sig", 1 + 4 * rows * b, 4 * rows)) for b in range(bands)]
    return signed.where("sig is not null").select("h", F.explode(F.array(*pieces)).alias("key")).distinct()


def candidate_links(signed: DataFrame, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """(a, b): stars of the texts that share a band."""
    keys = durable(_band_keys(signed, bands, rows), "bands")
    hubs = keys.groupBy("key").agg(F.min("h").alias("a"), F.count(F.lit(1)).alias("n")).where("n > 1").select("key", "a")
    return keys.join(hubs, "key").where("h <> a").select("a", F.col("h").alias("b")).distinct()


def _links_in_group(h: np.ndarray, side: np.ndarray, sig: np.ndarray, bags_of, threshold: float) -> list[tuple[int, int]]:
    """Links that connect what the pairs of this group connect. Pairs within side 1 are left out.

    ``bags_of`` gives the multisets of some of the texts: only of those that look near to another one by their signatures.
    """
    n, registers = len(h), sig.shape[1]
    floor = registers * (threshold - 5 * np.sqrt(threshold * (1 - threshold) / registers))
    looks: list[np.ndarray] = []
    for i in range(n):
        later = np.arange(i + 1, n)
        later = later[(side[later] == 0) | (side[i] == 0)]
        looks.append(later[np.count_nonzero(sig[later] == sig[i], axis=1) >= floor])
    needed = np.unique(np.concatenate([np.flatnonzero([len(x) > 0 for x in looks]), *looks]).astype(np.int64))
    bags = dict(zip(needed.tolist(), bags_of(needed), strict=True))
    root, links = np.arange(n), []
    mass = np.zeros(n, np.int64)
    mass[needed] = [bags[i][1].sum() for i in needed.tolist()]
    for i in range(n):
        others = looks[i][root[looks[i]] != root[i]]
        others = others[np.minimum(mass[others], mass[i]) >= threshold * np.maximum(mass[others], mass[i])]
        for j in others.tolist():
            if root[j] != root[i] and similarity(bags[i], bags[j]) >= threshold:
                root[root == root[j]] = root[i]
                links.append((int(h[i]), int(h[j])))
    return links


def verified_links(docs: DataFrame, signed: DataFrame, links: DataFrame, words: int = WORDS, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, block: int = BLOCK, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """(a, b): links of texts at or above ``threshold`` that connect each class."""
    links = durable(links, "candidates")
    ends = links.select(F.col("a").alias("v")).union(links.select(F.col("b").alias("v")))
    degree = ends.groupBy("v").agg(F.count(F.lit(1)).alias("degree"))
    members = connected_components(degree.select("v"), links, "cand").join(degree, "v")
    sizes = members.groupBy("root").agg(F.count(F.lit(1)).alias("n"), F.max_by("v", "degree").alias("leader"))
    members = durable(members.join(sizes, "root").select(F.col("v").alias("h"), "root", "n", "leader"), "members")
    n_members = members.count()
    near = bounded_broadcast(members, n_members, broadcast_rows)
    # one text for each member; the least identifier stands for all copies
    firsts = signed.join(near.select("h"), "h").groupBy("h").agg(F.min(F.struct(F.col("doc_id"), F.col("sig"))).alias("first"))
    firsts = durable(firsts.select("h", F.col("first.doc_id").alias("first_id"), F.col("first.sig").alias("sig")).join(members, "h"), "firsts")
    keyed = docs.select(F.col("doc_id").alias("d"), text_hash().alias("hh"), text_or_empty().alias("text"))
    on = keyed["d"].eqNullSafe(F.col("first_id")) & (keyed["hh"] == F.col("h"))
    full = keyed.join(bounded_broadcast(firsts, n_members, broadcast_rows // 5), on).select("h", "root", "n", "leader", "sig", "text")
    texts = durable(full, "texts")
    room = texts.groupBy("root").agg(F.greatest(F.lit(2), F.least(F.lit(block), F.expr(f"cast({BLOCK_BYTES} * count(1) / greatest(1, sum(octet_length(text))) as int)"))).alias("block"))
    texts = texts.join(bounded_broadcast(room, n_members, broadcast_rows), "root")
    kind = "a bigint, b bigint"

    small = texts.where(F.col("n") <= F.col("block")).select("root", F.lit(0).alias("i"), F.lit(0).alias("j"), F.lit(False).alias("cross"), "h", F.lit(0).alias("side"), "sig", "text")
    large = texts.where(F.col("n") > F.col("block"))
    # parts of a large component, each with a copy of its leader's text
    parts = F.greatest(F.lit(1), F.ceil(F.col("n") / F.col("block"))).cast("int")
    dealt = large.withColumn("part", F.pmod(F.xxhash64("h"), parts).cast("int")).withColumn("side", F.lit(0))
    lead = large.where("h = leader").dropDuplicates(["root"]).withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1))).withColumn("side", F.lit(1))

    def against(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        side = table.column("side").to_numpy()
        own = table.filter(pa.array(side == 0)).combine_chunks()
        leader = _bags(table.filter(pa.array(side == 1)).column("text").combine_chunks()[:1], words)[0]
        linked = [h == own_leader or similarity(x, leader) >= threshold for x, h, own_leader in zip(_bags(own.column("text").combine_chunks(), words), own.column("h").to_pylist(), own.column("leader").to_pylist(), strict=True)]
        textkit.trim()
        return own.select(["h", "root", "n", "leader", "block", "sig", "text"]).append_column("linked", pa.array(linked, pa.bool_()))

    checked = dealt.unionByName(lead).groupBy("root", "part").applyInArrow(against, "h bigint, root bigint, n bigint, leader bigint, block int, sig binary, text string, linked boolean")
    checked = durable(checked, "checked")
    led = checked.where("linked and h <> leader").select(F.col("leader").alias("a"), F.col("h").alias("b")).distinct()

    open_n = checked.where("not linked").groupBy("root").agg(F.count(F.lit(1)).alias("open"))
    blocks = checked.join(open_n, "root").withColumn("u", F.ceil(F.col("open") / F.col("block"))).withColumn("w", F.ceil((F.col("n") - F.col("open")) / F.col("block")))
    number = lambda k: F.pmod(F.xxhash64("h"), F.greatest(F.col(k), F.lit(1))).cast("int")
    upto = lambda k: F.sequence(F.lit(0), (F.greatest(F.col(k), F.lit(1)) - 1).cast("int"))
    rest, done = blocks.where("not linked").withColumn("own", number("u")), blocks.where("linked").withColumn("own", number("w"))
    among = rest.withColumn("k", F.explode(upto("u"))).select("root", F.least("own", "k").alias("i"), F.greatest("own", "k").alias("j"), F.lit(False).alias("cross"), "h", F.lit(0).alias("side"), "sig", "text")
    open_side = rest.withColumn("k", F.explode(upto("w"))).select("root", F.col("own").alias("i"), F.col("k").alias("j"), F.lit(True).alias("cross"), "h", F.lit(0).alias("side"), "sig", "text")
    done_side = done.withColumn("k", F.explode(upto("u"))).select("root", F.col("k").alias("i"), F.col("own").alias("j"), F.lit(True).alias("cross"), "h", F.lit(1).alias("side"), "sig", "text")

    def in_group(table: pa.Table) -> pa.Table:
        table = table.combine_chunks()
        h, first = np.unique(table.column("h").to_numpy(), return_index=True)
        table = table.take(pa.array(first))
        sig = np.frombuffer(b"".join(table.column("sig").to_pylist()), np.uint32).reshape(len(h), bands * rows)
        textkit.trim()
        text = table.column("text").combine_chunks()
        found = _links_in_group(h, table.column("side").to_numpy(), sig, lambda rows: _bags(text.take(pa.array(rows)), words), threshold)
        return pa.table({"a": pa.array([x for x, _ in found], pa.int64()), "b": pa.array([x for _, x in found], pa.int64())})

    groups = small.union(among).union(open_side).union(done_side)
    return groups.groupBy("root", "i", "j", "cross").applyInArrow(in_group, kind).union(led)


def near_classes(docs: DataFrame, words: int = WORDS, threshold: float = THRESHOLD, bands: int = BANDS, rows: int = ROWS, block: int = BLOCK, broadcast_rows: int = BROADCAST_ROWS, with_hash: bool = False) -> DataFrame:
    """doc_id, class_id (least identifier of the class), class_size and kept, for every document."""
    signed = durable(signatures(docs, words, bands, rows), "signatures")
    found = durable(verified_links(docs, signed, candidate_links(signed, bands, rows), words, threshold, bands, rows, block, broadcast_rows), "links")
    ends = found.select(F.col("a").alias("v")).union(found.select(F.col("b").alias("v"))).distinct()
    roots = durable(connected_components(ends, found, "class"), "roots")
    # texts that are alone and have no link need no look-up
    by_text = signed.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("doc_id").alias("first"))
    linked = by_text.join(bounded_broadcast(roots, roots.count(), broadcast_rows), F.col("h") == F.col("v"), "left")
    several = durable(linked.where("n > 1 or root is not null").select("h", F.coalesce("root", "h").alias("root"), "n", "first"), "several")
    winner = F.min(F.struct(F.col("first").isNull().alias("none"), F.col("first").alias("class_id"), F.col("h").alias("keep_h")))
    sums = several.groupBy("root").agg(winner.alias("w"), F.sum("n").alias("class_size"))
    lookup = durable(several.select("h", "root").join(sums, "root").select("h", "w.class_id", "w.keep_h", "class_size"), "classes")
    out = signed.select("doc_id", "h").join(bounded_broadcast(lookup, lookup.count(), broadcast_rows), "h", "left")
    alone = F.col("class_size").isNull()
    out = out.withColumn("class_id", F.when(alone, F.col("doc_id")).otherwise(F.col("class_id")))
    kept = F.col("doc_id").eqNullSafe(F.col("class_id")) & (F.coalesce("keep_h", "h") == F.col("h"))
    return out.select("doc_id", *(["h"] if with_hash else []), "class_id", F.coalesce("class_size", F.lit(1)).alias("class_size"), kept.alias("kept"))


def near_dedup(docs: DataFrame, broadcast_rows: int = BROADCAST_ROWS, **options) -> DataFrame:
    """Rows of ``docs`` of which one stays for each class, with all their columns.

    Only identifiers that go, and those that come more than once, are joined back.
    """
    classes = durable(near_classes(docs, broadcast_rows=broadcast_rows, with_hash=True, **options), "near")
    goes = classes.groupBy(F.col("doc_id").alias("id"), "h").agg(F.max("kept").alias("kept"), F.count(F.lit(1)).alias("n")).where("not kept or n > 1")
    goes = durable(goes, "goes")
    goes = bounded_broadcast(goes, goes.count(), broadcast_rows)
    # rows travel whole under one name, so that no column of theirs can clash
    keyed = docs.select(text_hash().alias("own"), F.col("doc_id").alias("own_id"), F.struct("*").alias("row"))
    on = F.col("own_id").eqNullSafe(F.col("id")) & (F.col("own") == F.col("h"))
    once = keyed.join(goes, on, "left_anti").select("row.*")
    one = Window.partitionBy("own", "own_id").orderBy(F.lit(0))
    again = keyed.join(goes.where("kept"), on).select("own", "own_id", "row").withColumn("rank", F.row_number().over(one))
    return once.union(again.where("rank = 1").select("row.*"))
