"""Language identification by hyperdimensional profiles.

Every letter has a random vector of signs.  An n-gram's vector binds (multiplies) its letters' vectors, each
permuted by its place; a text's vector bundles (adds) those of its n-grams; a language's prototype bundles its
texts.  A text gets the language of the largest cosine.  Bundling is linear, so the product of a text with a
prototype is the sum of its n-grams' products, which are taken once; the text's own norm is the same for all.
Letters are those of any script, each with a vector of its own that its code point seeds.
"""

from __future__ import annotations

import functools
import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from wsample.llm.common import by_batch, text_of

DIMENSIONS = 2048
#: Characters taken at once.
SLICE = 1_000_000
#: N-grams whose products a worker remembers, and n-grams whose vectors it makes at once.
REMEMBERED, AT_ONCE = 500_000, 2048
#: Rows expected beyond twice those wanted, where few are wanted.
SPARE = 200
#: Bits of a code point in an n-gram's code.
POINT = 21


@functools.lru_cache(maxsize=1)
def _table() -> np.ndarray:
    """Each code point that is a letter, as itself; 0 for any other character."""
    return np.fromiter((c if chr(c).isalpha() else 0 for c in range(0x110000)), np.int64, 0x110000)


@functools.lru_cache(maxsize=20_000)
def letter_vector(point: int, dimensions: int, seed: int) -> np.ndarray:
    """A letter's random signs, from the seed and its code point; 0 stands for what is between words."""
    return np.random.Generator(np.random.Philox(np.random.SeedSequence([seed, point]))).choice(np.array([-1, 1], np.int8), dimensions)


def gram_vectors(codes: np.ndarray, dimensions: int, seed: int) -> np.ndarray:
    """Vectors of n-grams: their letters' vectors, permuted by place and bound."""
    out = np.ones((len(codes), dimensions), np.int8)
    for place in range(3):
        points, of = np.unique(codes >> POINT * (2 - place) & (1 << POINT) - 1, return_inverse=True)
        letters = np.stack([np.roll(letter_vector(int(c), dimensions, seed), 2 - place) for c in points]) if len(points) else out
        out *= letters[of]
    return out


def _slices(text: str):
    """The text lower-cased between spaces, in slices that overlap by two characters."""
    text = f" {text.lower()} "
    if len(text) <= SLICE:
        yield text
    else:
        for at in range(0, len(text) - 2, SLICE - 2):
            yield text[at : at + SLICE]


def _grams(parts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Gram codes at every character of the joined parts (0 where one would cross), part starts, and letters a part."""
    lengths = np.fromiter(map(len, parts), np.int64, len(parts))
    s = _table()[np.frombuffer("".join(parts).encode("utf-32-le", "surrogatepass"), "<u4")]
    starts = np.cumsum(lengths) - lengths
    g = np.zeros(len(s), np.int64)
    g[:-2] = (s[:-2] << POINT | s[1:-1]) << POINT | s[2:]
    g[starts + lengths - 1] = 0
    g[starts + lengths - 2] = 0
    return g, starts, np.add.reduceat((s > 0).astype(np.int64), starts)


def _packed(texts: list[str | None]):
    """(rows, parts): slices of the texts in packs of about SLICE characters."""
    rows, parts, size = [], [], 0
    for i, text in enumerate(texts):
        for part in _slices(text or ""):
            rows.append(i)
            parts.append(part)
            size += len(part)
            if size >= SLICE:
                yield rows, parts
                rows, parts, size = [], [], 0
    if rows:
        yield rows, parts


@dataclass(frozen=True)
class Profiles:
    """Unit prototypes, one row a language."""

    languages: list[str]
    prototypes: np.ndarray
    seed: int


class Products:
    """N-gram vectors times prototypes, each made once: (codes sorted, their products)."""

    def __init__(self, profiles: Profiles):
        self.profiles, self.forget = profiles, lambda: (np.zeros(0, np.int64), np.zeros((0, len(profiles.languages))))
        self.codes, self.values = self.forget()

    def of(self, codes: np.ndarray) -> np.ndarray:
        """Products of distinct sorted codes; code 0, without letters, has none."""
        new = np.setdiff1d(codes, self.codes, assume_unique=True)
        if len(new):
            if len(self.codes) + len(new) > REMEMBERED:
                self.codes, self.values = self.forget()
                new = codes
            p = self.profiles
            made = [gram_vectors(new[i : i + AT_ONCE], p.prototypes.shape[1], p.seed).astype(np.float32) @ p.prototypes.T for i in range(0, len(new), AT_ONCE)]
            both, values = np.concatenate([self.codes, new]), np.concatenate([self.values, *made])
            order = np.argsort(both, kind="stable")
            self.codes, self.values = both[order], values[order]
            self.values[self.codes == 0] = 0
        return self.values[np.searchsorted(self.codes, codes)]


def held_out(id_col: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, *, per_language: int = 2000, dimensions: int = DIMENSIONS, seed: int = 11, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Profiles:
    """Prototypes from at most ``per_language`` whole texts of each language, picked by a hash of their ids.

    Null labels and texts, and null ids, teach nothing.  ``docs`` holds the rows that may be learned from.
    """
    known = docs.where(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull()).select(F.col(id_col).alias("doc_id"), F.col(lang_col).alias("lang"))
    # first a share of each language by hash, in which twice the rows wanted are expected; then exactly those of the least hashes
    counts = F.broadcast(known.groupBy("lang").agg(F.count("*").alias("n")))  # a row a language, as the prototypes
    share = F.shiftrightunsigned(F.xxhash64("doc_id"), 11) / F.lit(2.0**53)
    known = known.join(counts, "lang").where(share <= F.lit(2.0 * per_language + SPARE) / F.col("n"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id").bitwiseXOR(F.lit(-(2**63)).cast("long")), "doc_id"))
    known = known.withColumn("k", rank).where(F.col("k") <= per_language)
    some = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.col(lang_col).alias("lang")).where("lang is not null and text is not null")
    some = some.join(F.broadcast(known.select("doc_id").distinct()), "doc_id", "left_semi").select("lang", "text")  # per_language rows a language at most

    def bundle(batches):
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            langs = batch.column(0).to_pylist()
            for rows, parts in _packed(batch.column(1).to_pylist()):
                g, starts, _ = _grams(parts)
                names = list(dict.fromkeys(langs[r] for r in rows))
                of = np.repeat(np.array([names.index(langs[r]) for r in rows]), np.diff([*starts, len(g)]))
                codes, which = np.unique(g, return_inverse=True)
                counts = np.bincount(of * len(codes) + which, minlength=len(names) * len(codes)).reshape(len(names), -1).astype(np.float64)
                counts[:, codes == 0] = 0  # no letters, nothing told
                for lo in range(0, len(codes), AT_ONCE):
                    added = counts[:, lo : lo + AT_ONCE] @ gram_vectors(codes[lo : lo + AT_ONCE], dimensions, seed).astype(np.float64)
                    for name, row in zip(names, added, strict=True):
                        sums[name] = sums.get(name, 0) + row
        for name, row in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([name] * dimensions, pa.string()), pa.array(np.arange(dimensions, dtype=np.int32)), pa.array(np.rint(row).astype(np.int64))], ["lang", "i", "n"])

    table = some.mapInArrow(bundle, "lang string, i int, n long").groupBy("lang", "i").agg(F.sum("n").alias("n")).toArrow()  # dimensions rows a language
    names = sorted(set(table["lang"].to_pylist()))
    prototypes = np.zeros((len(names), dimensions))
    place = {x: i for i, x in enumerate(names)}
    prototypes[[place[x] for x in table["lang"].to_pylist()], table["i"].to_numpy()] = table["n"].to_numpy()
    prototypes /= np.maximum(np.linalg.norm(prototypes, axis=1, keepdims=True), 1e-9)
    return Profiles(names, prototypes.astype(np.float32), seed)


_products: dict[bytes, Products] = {}


def remembered(profiles: Profiles) -> Products:
    """A worker's products with these profiles, kept between tasks; those with others go."""
    key = hashlib.sha256(profiles.prototypes.tobytes() + repr((profiles.languages, profiles.seed)).encode()).digest()
    if key not in _products:
        _products.clear()
        _products[key] = Products(profiles)
    return _products[key]


def identify(docs: DataFrame, profiles: Profiles, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) of every whole text; ``und`` and 0 for a null text, one without a letter, or without profiles.

    ``score`` is the best language's share of the positive products.
    """
    spark, names = docs.sparkSession, profiles.languages
    shared = spark.sparkContext.broadcast(profiles)  # some thousand floats a language

    def tell(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts, products = batch.column(1).to_pylist(), remembered(shared.value)
        dots, letters = np.zeros((len(texts), max(len(names), 1))), np.zeros(len(texts), np.int64)
        for rows, parts in _packed(texts):
            g, starts, found = _grams(parts)
            np.add.at(letters, rows, found)
            if names:
                codes, which = np.unique(g, return_inverse=True)
                np.add.at(dots, rows, np.add.reduceat(products.of(codes)[which], starts, axis=0, dtype=np.float64))
        best = dots.argmax(axis=1)
        up = np.maximum(dots, 0)
        share = np.divide(up[np.arange(len(texts)), best], up.sum(axis=1), out=np.zeros(len(texts)), where=up.sum(axis=1) > 0)
        told = (letters > 0) & bool(names)
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([names[b] if t else "und" for b, t in zip(best, told, strict=True)], pa.string()), pa.array(np.where(told, share, 0.0))], ["doc_id", "lang_pred", "score"])

    kind = docs.schema[id_col].dataType.simpleString()
    return by_batch(docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")), tell, f"doc_id {kind}, lang_pred string, score double", size_by="text")
