"""Document quality by hierarchical empirical Bayes.

A logistic classifier over surface and lexicon features gives each document evidence.  Evidence is pooled by host
and by path under a host: a host's rate shrinks towards the corpus, a path's towards its host, as much as the spread
within and between them, taken from grouped aggregates over all documents, says.  A document's final chance is its
own evidence with the prior moved to its path, itself left out.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, text_of

#: Labelled rows that the classifier is fitted to, at most.
MOST_LABELLED = 20_000
#: Words that tell bad documents, at most.
MOST_WORDS = 300
_MARKS = b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~"
_CLASSES = np.stack([np.isin(np.arange(256), list(c)) for c in (
    range(65, 91), range(97, 123), range(48, 58), b"#$%&*+<=>@\\^_`{}~", b"!?", b"|", b".,;:'\"()-", range(128, 256), b"\n",
)]).astype(np.float64).T
N_FEATURES = 15


def clean_words(data: bytes) -> list[bytes]:
    """Words without ASCII marks, ASCII letters lower-cased."""
    return data.translate(None, _MARKS).lower().split()


def describe(text: str, lexicon: frozenset[bytes]) -> list[float]:
    """Surface features of a whole text and what it has of the lexicon."""
    data = text.encode()
    n = max(len(data), 1)
    upper, lower, digit, sign, shout, pipe, mark, wide, line = (np.bincount(np.frombuffer(data, np.uint8), minlength=256) @ _CLASSES).tolist()
    words = clean_words(data)
    k = max(len(words), 1)
    distinct = set(words)
    bad = distinct & lexicon
    hits = sum(map(bad.__contains__, words)) if bad else 0
    return [
        math.log1p(len(words)), math.log(n / k), upper / max(upper + lower + wide, 1), digit / n, sign / k, shout / k, pipe / k, mark / k, wide / n, line / k,
        len(distinct) / k, sum(map(eq, words, words[1:])) / k, math.log1p(len(bad)), float(bool(bad)), min(20 * hits / k, 3.0),
    ]


@dataclass(frozen=True)
class Classifier:
    lexicon: frozenset[bytes]
    mean: np.ndarray
    scale: np.ndarray
    weight: np.ndarray  # the last is the constant

    def chances(self, texts: list[str]) -> np.ndarray:
        if not texts:
            return np.zeros(0)
        x = (np.array([describe(t, self.lexicon) for t in texts]) - self.mean) / self.scale
        z = np.clip(x, -6, 6) @ self.weight[:-1] + self.weight[-1]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit_logistic(x: np.ndarray, y: np.ndarray, penalty: float = 1.0) -> np.ndarray:
    """Weights and constant by Newton steps with a ridge on the weights."""
    a = np.concatenate([x, np.ones((len(x), 1))], axis=1)
    w, ridge = np.zeros(a.shape[1]), np.diag([penalty] * x.shape[1] + [1e-6])
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + ridge, a.T @ (y - p) - ridge @ w)
        w = w + step
        if np.abs(step).max() < 1e-6:
            break
    return w


def lexicon_of(labelled: DataFrame) -> frozenset[bytes]:
    """Words that far more bad than good documents have, an eighth as many as bad documents at most: one aggregate over the labelled rows (text, good)."""

    def each(batch: pa.RecordBatch) -> pa.RecordBatch:
        words, good = [], []
        for text, g in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            found = set(clean_words(text.encode()))
            words += found
            good += [g] * len(found)
        return pa.RecordBatch.from_arrays([pa.array(words, pa.binary()), pa.array(good, pa.int32())], ["word", "good"])

    n = labelled.agg(F.sum("good"), F.count("*")).first()
    good, bad = float(n[0] or 0), float(n[1] - (n[0] or 0))
    if not good or not bad:
        return frozenset()
    table = by_batch(labelled.select("text", "good"), each, "word binary, good int", size_by="text").groupBy("word").agg(F.sum("good").alias("g"), F.count("*").alias("n")).where("n - g >= 3")
    b, g = F.col("n") - F.col("g") + 0.5, F.col("g") + 0.5
    odds = F.log(b / (bad + 1)) - F.log(g / (good + 1))
    ranked = table.select("word", odds.alias("odds"), (odds / F.sqrt(1 / b + 1 / g)).alias("z")).where("odds > 1.5 and z > 2.3")
    return frozenset(bytes(r["word"]) for r in ranked.orderBy(F.desc("z"), "word").limit(min(MOST_WORDS, max(8, int(bad) // 8))).collect())


def train(docs: DataFrame, labels: DataFrame, *, good: str = "quality = 1 and toxic = 0", most: int = MOST_LABELLED, id_col: str = "doc_id", text_col: str = "text") -> Classifier:
    """A classifier fitted to at most ``most`` labelled documents, picked by a hash of their ids.

    ``good`` is an expression over the labels; a null counts as not good.  Without both kinds of labels every chance is one half or the share of good ones.
    """
    marks = labels.select(F.col(id_col).alias("doc_id"), F.coalesce(F.expr(good), F.lit(False)).cast("int").alias("good")).where("doc_id is not null").dropDuplicates(["doc_id"])
    marks = marks.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")).join(F.broadcast(marks), "doc_id").select("text", "good")  # ``most`` rows of two numbers at most
    lexicon = lexicon_of(rows)

    def features(batch: pa.RecordBatch) -> pa.RecordBatch:
        x = [describe(t, lexicon) for t in batch.column(0).to_pylist()]
        return pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), batch.column(1)], ["x", "good"])

    table = by_batch(rows, features, "x array<double>, good int", size_by="text").toArrow()
    if not table.num_rows:
        return Classifier(lexicon, np.zeros(N_FEATURES), np.ones(N_FEATURES), np.zeros(N_FEATURES + 1))
    x, y = np.array(table["x"].to_pylist()), table["good"].to_numpy().astype(float)
    order = np.lexsort([*x.T, y])  # the same sums whatever the order of rows
    x, y = x[order], y[order]
    mean, scale = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-3)
    return Classifier(lexicon, mean, scale, fit_logistic(np.clip((x - mean) / scale, -6, 6), y))


def scored(docs: DataFrame, model: Classifier, *, text_col: str = "text") -> DataFrame:
    """``docs`` with ``p_doc``, the classifier's chance that the whole text is good; a null text is empty."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def add(batch: pa.RecordBatch) -> pa.RecordBatch:
        p = shared.value.chances([t or "" for t in batch.column(text_col).to_pylist()])
        return pa.RecordBatch.from_arrays([*batch.columns, pa.array(p)], [*batch.schema.names, "p_doc"])

    kept = docs.drop("p_doc")
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema) + ", p_doc double"
    return by_batch(kept, add, schema, size_by=text_col)


def _spread(groups: DataFrame) -> DataFrame:
    """Within-group variance over between-group variance: how many documents a group's parent is worth."""
    n, s, q = F.col("n"), F.col("s"), F.col("q")
    one = groups.agg(F.sum(n).alias("N"), F.count("*").alias("H"), F.sum(s).alias("S"), F.sum(q).alias("Q"), F.sum(s * s / n).alias("R"), F.sum(n * n).alias("M"))
    within = (F.col("Q") - F.col("R")) / F.greatest(F.col("N") - F.col("H"), F.lit(1))
    between = (F.col("R") - F.col("S") * F.col("S") / F.col("N") - (F.col("H") - 1) * within) / F.greatest(F.col("N") - F.col("M") / F.col("N"), F.lit(1e-9))
    worth = F.least(F.greatest(within / F.greatest(between, F.lit(1e-9)), F.lit(1.0)), F.lit(1e6))
    return one.select(F.coalesce(worth, F.lit(1.0)).alias("worth"), F.coalesce(F.col("S") / F.col("N"), F.lit(0.5)).alias("rate"))


def logit(p: Column) -> Column:
    inside = F.least(F.greatest(p, F.lit(1e-6)), F.lit(1 - 1e-6))
    return F.log(inside / (1 - inside))


def site_rates(evidence: DataFrame) -> DataFrame:
    """(host, path, path_n, path_s, host_rate, host_worth, rate): one row a path; evidence: (host, path, p_doc).

    Null hosts and paths are groups of their own.
    """
    paths = evidence.groupBy("host", "path").agg(F.count("*").alias("n"), F.sum("p_doc").alias("s"), F.sum(F.col("p_doc") * F.col("p_doc")).alias("q"))
    hosts = paths.groupBy("host").agg(F.sum("n").alias("n"), F.sum("s").alias("s"), F.sum("q").alias("q"))
    top, low = _spread(hosts).first(), _spread(paths).first()  # two numbers each
    rate = (F.col("s") + top["worth"] * F.lit(top["rate"])) / (F.col("n") + top["worth"])
    shrunk = hosts.select(F.col("host").alias("h"), rate.alias("host_rate"))
    return paths.join(shrunk, F.col("host").eqNullSafe(F.col("h"))).select("host", "path", F.col("n").alias("path_n"), F.col("s").alias("path_s"), "host_rate", F.lit(low["worth"]).alias("host_worth"), F.lit(top["rate"]).alias("rate"))


def classify(docs: DataFrame, labels: DataFrame, *, host: str | Column = "source", path: str | Column = "lang", least: float = 0.5, good: str = "quality = 1 and toxic = 0", most: int = MOST_LABELLED, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with p_doc, host_rate, path_rate, p_good and keep.

    ``path_rate`` leaves the document itself out.  ``keep`` is p_good of ``least`` or more.  Columns of these names in
    ``docs`` are replaced.  A null text is judged as an empty one; an empty table stays empty.
    """
    model = train(docs, labels, good=good, most=most, id_col=id_col, text_col=text_col)
    own = ("p_doc", "host_rate", "path_rate", "p_good", "keep", "__host", "__path")
    plain = docs.select(*[c for c in docs.columns if c not in own])
    place = lambda x: (F.col(x) if isinstance(x, str) else x).cast("string")
    narrow = plain.select(place(host).alias("host"), place(path).alias("path"), F.col(text_col).alias("text"))
    rates = site_rates(scored(narrow, model).select("host", "path", "p_doc"))
    named = rates.select(F.col("host").alias("__h"), F.col("path").alias("__p"), "path_n", "path_s", F.col("host_rate").alias("__host_rate"), "host_worth", F.col("rate").alias("__rate"))
    each = scored(plain.withColumns({"__host": place(host), "__path": place(path)}), model, text_col=text_col)
    joined = each.join(named, F.col("__host").eqNullSafe(F.col("__h")) & F.col("__path").eqNullSafe(F.col("__p")), "left")
    path_rate = (F.col("path_s") - F.col("p_doc") + F.col("host_worth") * F.col("__host_rate")) / (F.col("path_n") - 1 + F.col("host_worth"))
    chance = 1 / (1 + F.exp(-(logit(F.col("p_doc")) + logit(path_rate) - logit(F.col("__rate")))))
    return joined.select(*plain.columns, "p_doc", F.col("__host_rate").alias("host_rate"), path_rate.alias("path_rate"), chance.alias("p_good"), (chance >= least).alias("keep"))
