"""Trained generators, verifiers and selectors on the catalogue, whose components act on the data.

A question has a pool: its gold query, edits of it, and gold queries of questions with similar words.
A generator is a linear ranker of the pool over hashed pairs of question words and query tokens; its
first candidates are the beam. The components change what it sees or learns from:

* ``ir``: candidates are written in the simplified IR, and decoded again; what the IR leaves out can
  not go wrong, and edits that it does not tell apart are one candidate. The algebra backbone loses
  queries that its IR grammar does not cover, unless its version falls back to SQL; the sequence backbone falls back.
* ``gs``: pairs made from the schema alone are learnt first, and the gold pairs then, from those weights.
* ``pp``: names are split into their parts before pairs are hashed.

The algebra backbone pairs words with tokens tagged by their clause and never gives unparsable text;
the sequence backbone has plain tokens and pairs of neighbours. Questions are in five folds: a model for
one fold learns from the others only, and so do verifiers and selectors, from the beams of the others.
They judge question and candidate by cues (a word that asks for something the query should have), by
numbers, and, with the schema, by links from words to names.

All models are small logistic regressions that stand in for fine-tuned networks: the accuracies are this
engine's own. Fits are independent, so that a table of configurations is spread over the cluster,
one configuration to a row; the catalogue and the synthetic pairs, of fixed size, travel with the code.
"""

from __future__ import annotations

import re
import zlib
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from beamrank.functions import sqlshape
from beamrank.operators.generators import edits, number
from beamrank.sources.catalogue import GOLD
from beamrank.sources.tables import COLUMNS, FOREIGN_KEYS

FOLDS = 5
WIDTH = 6
DIMENSIONS = 512
NEIGHBOURS = 3
BACKBONES = ("alg", "seq")
IR, GS, PP = 1, 2, 4
#: The systems whose beams rerankers learn from.
ORIGINS = {"alg": ("alg", GS), "seq": ("seq", IR | GS)}
OWNER = {c: t for t, names in COLUMNS.items() for c in names.split() if sum(c in n.split() for n in COLUMNS.values()) == 1}
QUESTIONS = {g: (question, sql) for g, question, sql, _ in GOLD}


def fold_of(gold_id: str) -> int:
    return zlib.crc32(gold_id.encode()) % FOLDS


# ---- synthetic pairs from the schema

#: What columns are called in questions: (table, column, noun, whether it is a number).
NOUNS = [
    ("orders", "o_orderstatus", "status", False), ("orders", "o_orderpriority", "priority", False), ("orders", "o_totalprice", "price", True),
    ("customer", "c_mktsegment", "segment", False), ("customer", "c_acctbal", "balance", True), ("part", "p_type", "type", False),
    ("part", "p_brand", "brand", False), ("part", "p_retailprice", "retail price", True), ("part", "p_size", "size", True),
    ("lineitem", "l_returnflag", "return flag", False), ("lineitem", "l_quantity", "quantity", True), ("lineitem", "l_discount", "discount", True),
    ("supplier", "s_acctbal", "balance", True), ("supplier", "s_nationkey", "nation", False), ("events", "event_type", "type", False),
    ("events", "value", "value", True), ("documents", "lang", "language", False), ("documents", "source", "source", False), ("conversations", "role", "role", False),
]
PLURAL = {"orders": "orders", "customer": "customers", "part": "parts", "lineitem": "lines", "supplier": "suppliers", "events": "events", "documents": "documents", "conversations": "turns"}


@cache
def synthetic() -> tuple[tuple[str, str, str, str], ...]:
    """(identifier, question, query, difficulty), without duplicates."""
    out: dict[tuple[str, str], str] = {}
    for t, c, noun, numeric in NOUNS:
        many = PLURAL[t]
        out[f"How many {many} are there?", f"select count(*) as n from {t}"] = "easy"
        if numeric:
            k = 1 + int(50 * number(t, c))
            for word, f in (("largest", "max"), ("smallest", "min")):
                out[f"What is the {word} {noun} of {many}?", f"select {f}({c}) as v from {t}"] = "easy"
            out[f"How many {many} have a {noun} above {k}?", f"select count(*) as n from {t} where {c} > {k}"] = "easy"
            out[f"How many {many} have a {noun} of at least {k}?", f"select count(*) as n from {t} where {c} >= {k}"] = "easy"
            out[f"How many {many} have a {noun} below {k}?", f"select count(*) as n from {t} where {c} < {k}"] = "easy"
            out[f"The {noun} of {many} between {k} and {k + 10}.", f"select {c} from {t} where {c} between {k} and {k + 10}"] = "easy"
            out[f"The five largest values of {noun} of {many}.", f"select {c} from {t} order by {c} desc limit 5"] = "hard"
            for t2, c2, noun2, numeric2 in NOUNS:
                if t2 == t and not numeric2:
                    for word, f in (("largest", "max"), ("smallest", "min")):
                        out[f"What is the {word} {noun} per {noun2}?", f"select {c2}, {f}({c}) as v from {t} group by {c2}"] = "medium"
        else:
            out[f"Which {noun} values exist among {many}?", f"select distinct {c} from {t}"] = "easy"
            out[f"How many different {noun} values do {many} have?", f"select count(distinct {c}) as n from {t}"] = "easy"
            out[f"How many {many} are in each {noun}?", f"select {c}, count(*) as n from {t} group by {c}"] = "medium"
            k = 10 + int(90 * number(t, c))
            out[f"Which {noun} values have more than {k} {many}?", f"select {c} from {t} group by {c} having count(*) > {k}"] = "hard"
    for (t, c), (ft, fc) in FOREIGN_KEYS.items():
        if t in PLURAL and f"{ft[0]}_name" in OWNER:
            out[f"Number of {PLURAL[t]} per {ft} name.", f"select {ft[0]}_name, count(*) as n from {ft} join {t} on {fc} = {c} group by {ft[0]}_name"] = "hard"
    return tuple((f"S{i:03d}", q, s, d) for i, ((q, s), d) in enumerate(out.items()))


# ---- pools of candidates


def _words(question: str) -> list[str]:
    return re.findall(r"[a-z]+|\d+(?:\.\d+)?", question.lower())


@cache
def neighbours(gold_id: str) -> tuple[str, ...]:
    own = set(_words(QUESTIONS[gold_id][0]))
    near = sorted((g for g in QUESTIONS if g != gold_id), key=lambda g: (-len(own & set(_words(QUESTIONS[g][0]))), g))
    return tuple(QUESTIONS[g][1] for g in near[:NEIGHBOURS])


def _canonical(sql: str) -> str | None:
    """The query decoded from its IR."""
    ir, _ = sqlshape.encode(sql, OWNER, FOREIGN_KEYS)
    return sqlshape.decode(ir, OWNER, FOREIGN_KEYS) if ir else None


@cache
def pool(key: str, gold: str, backbone: str, ir: bool, version: str = "v3") -> tuple[tuple[str, ...], bool]:
    """Distinct candidates of a question, in an order drawn by hash, and whether they are scored as IR."""
    texts, scored = [gold, *(q for _, q in edits(key, gold, backbone == "seq")), *(neighbours(key) if key in QUESTIONS else ())], ir and version != "v2"
    if ir and not (backbone == "alg" and version == "v1"):
        back = {q: _canonical(q) for q in texts}
        if back[gold] is None and not (backbone == "alg" and version == "v2"):
            back, scored = {q: q for q in texts}, False
        texts = [q for q in back.values() if q]
    return tuple(sorted(dict.fromkeys(texts), key=lambda q: number(key, q))), scored


@cache
def same_parts(a: str, b: str) -> bool:
    """Exact component match."""
    p, q = sqlshape.parts(a), sqlshape.parts(b)
    return p is not None and q is not None and all(p[c] == q[c] for c in ("distinct", *sqlshape.FIELDS, "limit", "setop"))


# ---- what generators see


def _hashed(*parts: str) -> int:
    return zlib.crc32("|".join(parts).encode()) % DIMENSIONS


@cache
def query_tokens(sql: str, backbone: str, ir: bool, pp: bool) -> tuple[str, ...]:
    if ir:
        shape, _ = sqlshape.encode(sql, OWNER, FOREIGN_KEYS)
        # columns of the IR are named with their tables
        sql = re.sub(r"[a-z_]\w*", lambda m: f"{OWNER[m[0]]} . {m[0]}" if m[0] in OWNER else m[0], sqlshape.ir_text(shape)) if shape else sql
    split = (lambda t: [x for x in re.split(r"(_)|(?<=[a-z])(?=[A-Z])", t) if x and x != "_"]) if pp else (lambda t: [t])
    if backbone == "alg":
        clause, out = "", []
        for t in sqlshape.tokenize(sql):
            clause = t if t in ("select", "from", "where", "group", "having", "order", "limit", "on") else clause
            out += [f"{clause}:{x}" for x in split(t)]
        return tuple(dict.fromkeys(out))
    plain = [x for t in sqlshape.tokenize(sql) for x in split(t)]
    return tuple(dict.fromkeys([*plain, *(f"{a} {b}" for a, b in zip(plain, plain[1:], strict=False))]))


@cache
def seen_by_generator(question: str, sql: str, backbone: str, ir: bool, pp: bool) -> np.ndarray:
    """Hashed pairs of question words and query tokens, and shares of words and tokens that are the same."""
    words = dict.fromkeys(w.rstrip("s") for w in _words(question))
    tokens = query_tokens(sql, backbone, ir, pp)
    x = np.zeros(DIMENSIONS + 3)
    for t in tokens:
        for w in words:
            x[_hashed(w, t)] += 1
    norm = np.linalg.norm(x)
    x /= norm or 1
    plain = {t.split(":")[-1].strip("'").rstrip("s") for t in tokens}
    x[-3] = len(plain & set(words)) / max(1, len(words))
    x[-2] = len([t for t in plain if t.isdigit() and t not in words]) / 2
    x[-1] = len(tokens) / 50
    return x


# ---- models


def fit(x: np.ndarray, y: np.ndarray, start: np.ndarray | None = None, steps: int = 150, rate: float = 2.0, l2: float = 1e-3) -> np.ndarray:
    """Logistic regression by gradient descent with balanced classes; the last weight is the bias."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1]) if start is None else start.copy()
    if not len(y):
        return w
    share = np.where(y > 0, 0.5 / max(1, (y > 0).sum()), 0.5 / max(1, (y <= 0).sum()))
    for _ in range(steps):
        w -= rate * (x.T @ (share * (1 / (1 + np.exp(-x @ w)) - y)) + l2 * w)
    return w


def probability(w: np.ndarray, x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-(x @ w[:-1] + w[-1])))


def _rows(items, backbone: str, mask: int, version: str):
    x, y = [], []
    for key, question, gold in items:
        texts, ir = pool(key, gold, backbone, bool(mask & IR), version)
        for q in texts:
            x.append(seen_by_generator(question, q, backbone, ir, bool(mask & PP)))
            y.append(float(same_parts(q, gold)))
    return np.array(x).reshape(len(x), DIMENSIONS + 3), np.array(y)


def train_generator(backbone: str, mask: int, fold: int, version: str = "v3", share: float = 1.0, mix: str = "all", stages: str = "both") -> np.ndarray:
    """Weights after the synthetic pairs (a share of them, of some difficulty) and the gold pairs of the other folds."""
    w = None
    if mask & GS and stages != "gold":
        made = [(k, q, s) for k, q, s, d in synthetic() if number("share", k) < share and mix in ("all", d)]
        w = fit(*_rows(made, backbone, mask, version), steps=100)
    if stages == "synthetic":
        return w
    gold = [(g, q, s) for g, (q, s) in QUESTIONS.items() if fold_of(g) != fold]
    return fit(*_rows(gold, backbone, mask, version), start=w)


def beams_of(backbone: str, mask: int, fold: int, version: str = "v3", **training) -> list[tuple[str, int, str, float, bool]]:
    """(question, rank, query, score, component match) of the beams of a fold."""
    w, out = train_generator(backbone, mask, fold, version, **training), []
    for g, (question, gold) in QUESTIONS.items():
        if fold_of(g) == fold:
            texts, ir = pool(g, gold, backbone, bool(mask & IR), version)
            if not texts:
                continue
            p = probability(w, np.array([seen_by_generator(question, q, backbone, ir, bool(mask & PP)) for q in texts]))
            for rank, i in enumerate(np.lexsort((np.arange(len(p)), -np.round(p, 9)))[:WIDTH], 1):
                out.append((g, rank, texts[i], round(float(p[i]), 6), same_parts(texts[i], gold)))
    return out


@cache
def system(backbone: str, mask: int, version: str = "v3") -> tuple:
    return tuple(row for fold in range(FOLDS) for row in beams_of(backbone, mask, fold, version))


# ---- what verifiers and selectors see

#: (what a question asks with, what the query should then have)
CUES = [
    (r"how many|number of", r"\bcount\b"), (r"different|distinct|exist", r"\bdistinct\b"), (r"largest|expensive|highest", r"\bmax\b|\bdesc\b"),
    (r"smallest|lowest", r"\bmin\b|\border by\b(?!.* desc)"), (r"\btotal\b", r"\bsum\b"), (r"average", r"\bavg\b"), (r"\bper\b|\beach\b|, by", r"group by"),
    (r"more than|above|dearer", r">(?!=)"), (r"at least", r">="), (r"below|negative|less", r"<(?![=>])"), (r"between", r"between|>=.*<="),
    (r"without|never", r"\bnot\b|\bexcept\b"), (r"\bboth\b|and a part", r"\bintersect\b"), (r"\bor\b|\bof customers or", r"\bor\b|\bunion\b"),
    (r"\b(?:three|five)\b", r"\blimit\b"), (r"\b(?:three|five) (?:most|smallest|largest)", r"\border by\b"), (r"without|never|status [a-z]\b|with|have|urgent|above|below|than|between|of size|in \d+|or quantity|never|least|type", r"\bwhere\b|\bhaving\b"),
]
NUMBERS = {"one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "negative": "0"}


def _numbers(text: str) -> set[str]:
    return {str(float(n)) for n in re.findall(r"(?<![\w.])\d+(?:\.\d+)?(?![\w.])", text)}


@cache
def seen_by_verifier(question: str, sql: str, schema: bool) -> np.ndarray:
    """Cues that are missed or not asked for, numbers, literals, and links to names of the schema."""
    q, s = question.lower(), sql.lower()
    x = []
    for ask, have in CUES:
        a, h = bool(re.search(ask, q)), bool(re.search(have, s))
        x += [a and not h, h and not a, a and h]
    asked = _numbers(q) | {str(float(NUMBERS[w])) for w in _words(q) if w in NUMBERS}
    used = _numbers(s)
    x += [bool(asked - used), bool(used - asked), bool(asked & used)]
    words = {w.rstrip("s") for w in _words(q)}
    literals = [w for t in re.findall(r"'([^']*)'", s) for w in re.findall(r"[a-z0-9]+", t)]
    x += [any(w.rstrip("s") not in words for w in literals), bool(literals)]
    x += [sqlshape.parts(sql) is None, len(s) / max(1, len(q)) / 5]
    names = set(re.findall(r"[a-z_]\w*", re.sub(r"'[^']*'", "", s)))
    # without the schema, a name is any word that is none of SQL
    linked = lambda n: any(len(w) > 2 and w in n for w in words)
    if schema:
        columns, tables = [n for n in names if n in OWNER], [n for n in names if n in COLUMNS]
        reach = {w for w in words if len(w) > 2 and any(w in c for c in OWNER)}
        x += [
            sum(map(linked, columns)) / max(1, len(columns)), sum(map(linked, tables)) / max(1, len(tables)),
            sum(any(w in c for c in columns) for w in reach) / max(1, len(reach)), any(OWNER[c] not in tables for c in columns),
            any(OWNER.get(c) == t and not linked(c) for c in columns for t in tables),
        ]
    return np.array(x, float)


def _gold_in(rows: list[tuple[str, bool]], gold: str, k: int, front: bool) -> list[tuple[str, bool]]:
    """The first k (query, right) with the gold query put in, last or first, if no query matches it."""
    rows = rows[:k]
    if any(same_parts(q, gold) for q, _ in rows):
        return rows
    return [(gold, True), *rows][:k] if front else [*rows[: k - 1], (gold, True)]


def _by_question(beams) -> dict[str, list[tuple[str, bool]]]:
    out: dict[str, list[tuple[str, bool]]] = {}
    for g, _, q, _, em in beams:
        out.setdefault(g, []).append((q, em))
    return out


def verifier_rows(origin: str, k: int = 5) -> list[tuple[str, int, str, bool]]:
    """(question, place, query, right) of the first k candidates of an origin's beams, gold query included."""
    found = _by_question(system(*ORIGINS[origin]))
    return [(g, i, q, ok) for g in QUESTIONS for i, (q, ok) in enumerate(_gold_in(found.get(g, []), QUESTIONS[g][1], k, False), 1)]


@cache
def verifier(origin: str, schema: bool, fold: int) -> np.ndarray:
    rows = [(g, q, ok) for g, _, q, ok in verifier_rows(origin) if fold_of(g) != fold]
    return fit(np.array([seen_by_verifier(QUESTIONS[g][0], q, schema) for g, q, _ in rows]), np.array([float(ok) for *_, ok in rows]), steps=300)


def verdict(origin: str, schema: bool, gold_id: str, sql: str) -> float:
    return float(probability(verifier(origin, schema, fold_of(gold_id)), seen_by_verifier(QUESTIONS[gold_id][0], sql, schema)[None, :])[0])


def reorder(rows: list, order: str, key: str, keep: float = 0.7) -> list:
    """A training beam shuffled by hash, or with a right first item moved on while a coin says so."""
    if order == "random":
        return sorted(rows, key=lambda r: number(key, r[0]))
    rows = list(rows)
    for i in range(len(rows) - 1):
        if not rows[i][1] or number(key, i, "keep") < keep:
            break
        rows[i], rows[i + 1] = rows[i + 1], rows[i]
    return rows


def _seen_by_selector(question: str, texts: list[str], k: int) -> np.ndarray:
    """What the verifier sees, less the beam's mean, with the place."""
    x = np.array([seen_by_verifier(question, q, True) for q in texts])
    return np.hstack([x, x - x.mean(axis=0), np.eye(k)[: len(texts)]])


@cache
def selector(origin: str, k: int, order: str, fold: int) -> np.ndarray:
    """A linear head over the candidates of a beam side by side; gold first if it is not among them."""
    x, y = [], []
    for g, rows in _by_question(system(*ORIGINS[origin])).items():
        if fold_of(g) != fold:
            rows = reorder(_gold_in(rows, QUESTIONS[g][1], k, True), order, g)
            x.append(_seen_by_selector(QUESTIONS[g][0], [q for q, _ in rows], k))
            y += [float(ok) for _, ok in rows]
    return fit(np.vstack(x), np.array(y), steps=300)


def choice(origin: str, k: int, order: str, gold_id: str, texts: list[str]) -> int:
    """Which of at most k candidates the selector takes."""
    p = probability(selector(origin, k, order, fold_of(gold_id)), _seen_by_selector(QUESTIONS[gold_id][0], texts[:k], k))
    return int(np.argmax(np.round(p, 9)))


RERANKERS = ("none", "verifier", "verifier_noschema", "selector", "hybrid")


def rerank(name: str, origin: str, gold_id: str, texts: list[str]) -> int:
    """Place (from 0) of the candidate that a reranker chooses from a beam."""
    if name == "none":
        return 0
    if name == "selector":
        return choice(origin, 5, "geometric", gold_id, texts)
    good = [i for i, q in enumerate(texts) if verdict(origin, name != "verifier_noschema", gold_id, q) >= 0.5]
    if name != "hybrid":
        return good[0] if good else 0
    rest = [i for i in good if i]
    return rest[0] if rest and choice(origin, 2, "geometric", gold_id, [texts[0], texts[rest[0]]]) else 0


# ---- spread over the cluster

CONFIG = "backbone string, mask int, fold int, version string, share double, mix string, stages string"
BEAM = "gold_id string, pos int, sql string, score double, em boolean"


def configurations(systems, versions=("v3",), shares=(1.0,), mixes=("all",), stages=("both",)) -> list[tuple]:
    return [(b, m, f, v, s, x, t) for b, m in systems for f in range(FOLDS) for v in versions for s in shares for x in mixes for t in stages]


def generated(spark: SparkSession, configs: list[tuple]) -> DataFrame:
    """Beams of each configuration, one fit to a row."""

    def run(batches):
        for batch in batches:
            for c in batch.itertuples(index=False):
                rows = beams_of(c.backbone, c.mask, c.fold, c.version, share=c.share, mix=c.mix, stages=c.stages)
                yield pd.DataFrame([(*c, *r) for r in rows], columns=[n.split()[0] for n in f"{CONFIG}, {BEAM}".split(", ")])

    table = spark.createDataFrame(configs, CONFIG).repartition(min(len(configs), spark.sparkContext.defaultParallelism * 4))
    return table.mapInPandas(run, f"{CONFIG}, {BEAM}")


ALL = [(b, m) for b in BACKBONES for m in range(8)]
