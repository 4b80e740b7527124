"""Personal data in whole texts: rule spans, and spans that boosted trees add.  DataFrame functions only.

High-recall generators propose spans that may overlap.  A proposal that meets a span of the base rules (which check
address parts, digit counts and check digits) is a positive for that kind; one that does not, and has no word of the kind
before it, is a negative.  Format and context are its features, but neither the checks, nor what the kind's rule demands
anyway (trees would learn the rule and add nothing), nor the kind's own words.  Boosted trees are fitted to the counts of
each cell of feature values over all documents (one aggregate; up to MOST_CELLS cells are fitted on the driver, more of them
by sums over their table), become SQL
expressions, and get a threshold for each kind at which the proposals of a second half of the documents are positive often
enough.  A proposal above it that has a word of the kind before it and meets no base span is added.
"""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.llm.common import small_enough, text_of, written

KINDS = ("email", "ip", "card", "phone")
#: Each matches what the plain rule matches from left to right; possessive loops and the look-behind keep long runs linear.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for a rule to be worth running.
NEEDS = {"email": "@", "ip": ".", "card": None, "phone": "+"}
#: Proposals: addresses, also spelled out, and runs of at least seven digits under any punctuation; with the character before, if any.
ADDRESS = r"(?:^|[^A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++\x20?(?:@|[\[(]\x20?(?:at|AT)\x20?[\])])\x20?[A-Za-z0-9-]++(?:\x20?(?:\.|[\[(]\x20?(?:dot|DOT)\x20?[\])])\x20?[A-Za-z0-9-]++)++"
NUMBER = r"(?:^|[^0-9A-Za-z])[+(]?[0-9](?:[\x20().:-]{0,2}[0-9]){6,}+"
#: How the proposals proper begin.
BEGINS = {ADDRESS: "^[A-Za-z0-9._%+-]", NUMBER: "^[+(]?[0-9]"}
#: Up to so many cells of feature values are fitted on the driver; more stay a table, of which it gets sums by node, feature and value.
MOST_CELLS = 100_000
CONTEXT = 16
HINTS = {"email": r"mail|contact|write", "ip": r"\bip\b|host|server|addr", "card": r"card|visa|credit|pay", "phone": r"tel|phone|call|fax|mobil"}


def placed(text: Column, found: Column) -> Column:
    """array<struct<s,e,m>>: code-point places of matches that a scan from the left gave.

    No rule looks ahead, so a match's text cannot stand between the end of the match before and its own place.
    """

    def step(state: Column, m: Column) -> Column:
        at = F.array(_locate(m, text, state["pos"] + 1) - 1)
        return F.transform(at, lambda p: F.struct((p + F.char_length(m)).alias("pos"), F.concat(state["out"], F.array(F.struct(p.alias("s"), (p + F.char_length(m)).alias("e"), m.alias("m")))).alias("out")))[0]

    start = F.struct(F.lit(0).alias("pos"), F.array().cast("array<struct<s:int,e:int,m:string>>").alias("out"))
    return F.aggregate(found, start, step)["out"]


def _locate(sub: Column, text: Column, pos: Column) -> Column:
    return F.call_function("locate", sub, text, pos)


def digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def luhn(d: Column) -> Column:
    """Whether the check digit of a string of digits holds."""
    turned = F.reverse(d)

    def add(total: Column, i: Column) -> Column:
        x = F.substring(turned, i, F.lit(1)).cast("int")
        return total + F.when(i % 2 == 0, 2 * x - F.when(x > 4, 9).otherwise(0)).otherwise(x)

    return F.aggregate(F.sequence(F.lit(1), F.char_length(d)), F.lit(0), add) % 10 == 0


def valid(kind: str, m: Column) -> Column:
    if kind == "ip":
        bare = lambda p: F.regexp_replace(p, "^0+", "")
        return F.forall(F.split(m, r"\."), lambda p: (F.char_length(bare(p)) <= 3) & (F.coalesce(F.substring(bare(p), 1, 3).try_cast("int"), F.lit(0)) <= 255))
    n = F.char_length(digits(m))
    if kind == "card":
        return F.when(n.between(16, 19), luhn(digits(m))).otherwise(False)
    if kind == "phone":
        return n.between(8, 15)
    return F.lit(True)


def base_spans(text: Column, kind: str) -> Column:
    """array<struct<s,e,m>> of a rule's valid matches, without retries where one fails."""
    found = F.regexp_extract_all(text, F.lit(BASE[kind]), F.lit(0))
    if NEEDS[kind]:
        found = F.when(F.contains(text, F.lit(NEEDS[kind])), found).otherwise(F.array().cast("array<string>"))
    return F.filter(placed(text, found), lambda x: valid(kind, x["m"]))


#: Names of a proposal's features; all are small integers.
FEATURES = ("digits", "plus", "round", "dots", "dashes", "spaces", "colons", "first", "longest", "at", "length", "hint_email", "hint_ip", "hint_card", "hint_phone")

#: What a kind's base rule demands of each match.
DEMANDED = {"email": ("at", "dots"), "ip": ("dots",), "card": (), "phone": ("plus",)}


def features(text: Column, x: Column) -> list[Column]:
    """Format and context of a proposal, without what the rules check."""
    m = x["m"]
    count = lambda chars, most: F.least(F.char_length(F.regexp_replace(m, f"[^{chars}]", "")), F.lit(most))
    near = F.lower(F.substring(text, F.greatest(x["s"] + 1 - CONTEXT, F.lit(1)), F.least(F.lit(CONTEXT), x["s"])))
    longest = F.array_max(F.transform(F.split(m, "[^0-9]+"), lambda p: F.char_length(p)))
    values = [count("0-9", 25), count("+", 1), count("()", 1), count(".", 4), count("-", 4), count(" ", 4), count(":", 1), F.coalesce(F.substring(digits(m), 1, 1).try_cast("int"), F.lit(-1)), F.least(longest, F.lit(20)), count("@", 1), F.least(F.char_length(m) / 8, F.lit(5)).cast("int")]
    return [*values, *(F.when(near.rlike(HINTS[k]), 1).otherwise(0) for k in KINDS)]


def proposals(text: Column) -> Column:
    """array<struct<g,s,e,m>>: g is 0 for addresses and 1 for numbers.

    Matches hold the character before the proposal, so that their place is the one where the rule held; it is then cut off.
    """
    spelled_at = F.contains(text, F.lit("@")) | text.rlike(r"[\[(] ?(?:at|AT) ?[\])]")
    found = {0: (ADDRESS, F.when(spelled_at, F.regexp_extract_all(text, F.lit(ADDRESS), F.lit(0))).otherwise(F.array().cast("array<string>"))), 1: (NUMBER, F.regexp_extract_all(text, F.lit(NUMBER), F.lit(0)))}

    def cut(g: int, rule: str):
        def proper(x: Column) -> Column:
            lead = ((x["s"] > 0) | ~x["m"].rlike(BEGINS[rule])).cast("int")
            return F.struct(F.lit(g).alias("g"), (x["s"] + lead).alias("s"), x["e"].alias("e"), F.substring(x["m"], lead + 1, F.char_length(x["m"])).alias("m"))

        return proper

    return F.concat(*[F.transform(placed(text, spans), cut(g, rule)) for g, (rule, spans) in found.items()])


def meets(x: Column, spans: Column) -> Column:
    return F.exists(spans, lambda y: (y["s"] < x["e"]) & (x["s"] < y["e"]))


@dataclass(frozen=True)
class Tree:
    """Leaves are numbers; a node sends values up to ``cut`` to the left."""

    feature: str
    cut: int
    left: Tree | float
    right: Tree | float

    def sql(self, value) -> Column:
        side = lambda t: t.sql(value) if isinstance(t, Tree) else F.lit(t)
        return F.when(value(self.feature) <= self.cut, side(self.left)).otherwise(side(self.right))

    def of(self, row: dict) -> float:
        t = self.left if row[self.feature] <= self.cut else self.right
        return t.of(row) if isinstance(t, Tree) else t


def best_split(sums: dict[str, dict[int, list[float]]], names: tuple[str, ...], g: float, h: float, least: float) -> tuple[str, int] | None:
    """Feature and cut of most gain over none; sums: feature -> value -> gradients, curvatures and number."""
    best = (g * g / (h + 1) + 1e-6, None)
    for f in names:
        by = sums[f]
        total, a, b, n = sum(x[2] for x in by.values()), 0.0, 0.0, 0.0
        for cut in sorted(by)[:-1]:
            a, b, n = a + by[cut][0], b + by[cut][1], n + by[cut][2]
            if min(n, total - n) >= least and (gain := a * a / (b + 1) + (g - a) ** 2 / (h - b + 1)) > best[0]:
                best = (gain, (f, cut))
    return best[1]


def fit_trees(cells: list[tuple[dict, float, float]], *, names: tuple[str, ...] = FEATURES, rounds: int = 24, depth: int = 2, rate: float = 0.4, least: float = 4.0) -> tuple[float, list[Tree]]:
    """Start score and trees by Newton boosting of the logistic loss; cells: (features, positives, negatives)."""
    pos, neg = sum(p for _, p, _ in cells), sum(n for _, _, n in cells)
    start = math.log((pos + 1) / (neg + 1))
    score, trees = [start] * len(cells), []

    def grow(rows: list[int], level: int) -> Tree | float:
        grad = [0.0] * len(rows)
        hess = [0.0] * len(rows)
        for k, i in enumerate(rows):
            p, n = 1 / (1 + math.exp(-score[i])), cells[i][1] + cells[i][2]
            grad[k], hess[k] = cells[i][1] - n * p, n * p * (1 - p)
        g, h = sum(grad), sum(hess)
        leaf = rate * g / (h + 1)
        if not level:
            return leaf
        sums: dict[str, dict[int, list[float]]] = {f: {} for f in names}
        for f in names:
            for k, i in enumerate(rows):
                s = sums[f].setdefault(cells[i][0][f], [0.0, 0.0, 0.0])
                s[0] += grad[k]
                s[1] += hess[k]
                s[2] += cells[i][1] + cells[i][2]
        found = best_split(sums, names, g, h, least)
        if found is None:
            return leaf
        f, cut = found
        return Tree(f, cut, grow([i for i in rows if cells[i][0][f] <= cut], level - 1), grow([i for i in rows if cells[i][0][f] > cut], level - 1))

    for _ in range(rounds):
        tree = grow(list(range(len(cells))), depth)
        if not isinstance(tree, Tree):
            break
        trees.append(tree)
        score = [s + tree.of(c[0]) for s, c in zip(score, cells, strict=True)]
    return start, trees


def score_of(start: float, trees: list[Tree], value) -> Column:
    out = F.lit(start)
    for t in trees:
        out = out + t.sql(value)
    return out


def fit_table(cells: DataFrame, *, names: tuple[str, ...] = FEATURES, rounds: int = 24, depth: int = 2, rate: float = 0.4, least: float = 4.0) -> tuple[float, list[Tree]] | None:
    """:func:`fit_trees` of a written table of cells (features, pos, neg) of any number; None without positives or negatives.

    A level of a tree takes one aggregate, which gives a row a node, feature and value.
    """
    pos, neg = cells.agg(F.coalesce(F.sum("pos"), F.lit(0.0)), F.coalesce(F.sum("neg"), F.lit(0.0))).first()
    if not pos or not neg:
        return None
    start, trees = math.log((pos + 1) / (neg + 1)), []
    for _ in range(rounds):
        p, n = 1 / (1 + F.exp(-score_of(start, trees, F.col))), F.col("pos") + F.col("neg")
        each = cells.select(*names, n.alias("__n"), (F.col("pos") - n * p).alias("__g"), (n * p * (1 - p)).alias("__h"))
        leaves, splits, level = {}, {}, [()]
        for _ in range(depth):
            node = F.lit(None).cast("int")
            for k, path in enumerate(level):
                inside = F.lit(True)
                for f, cut, left in path:
                    inside = inside & (F.col(f) <= cut if left else F.col(f) > cut)
                node = F.when(inside, k).otherwise(node)
            values = F.explode(F.array(*[F.struct(F.lit(j).alias("f"), F.col(f).cast("int").alias("v")) for j, f in enumerate(names)])).alias("x")
            rows = each.select(node.alias("node"), values, "__g", "__h", "__n").where("node is not null").groupBy("node", "x.f", "x.v").agg(F.sum("__g"), F.sum("__h"), F.sum("__n")).collect()  # nodes x features x their few values
            sums: list[dict] = [{f: {} for f in names} for _ in level]
            for k, j, v, *total in rows:
                sums[k][names[j]][v] = total
            below = []
            for path, of in zip(level, sums, strict=True):
                g, h = (sum(x[i] for x in of[names[0]].values()) for i in (0, 1))
                leaves[path] = rate * g / (h + 1)
                if (found := best_split(of, names, g, h, least)) is None:
                    continue
                splits[path] = found
                for left in (True, False):
                    side = [x for v, x in of[found[0]].items() if (v <= found[1]) == left]
                    below.append((*path, (*found, left)))
                    leaves[below[-1]] = rate * sum(x[0] for x in side) / (sum(x[1] for x in side) + 1)
            level = below
            if not level:
                break
        if () not in splits:
            break

        def grown(path: tuple) -> Tree | float:
            if path not in splits:
                return leaves[path]  # noqa: B023
            return Tree(*splits[path], *(grown((*path, (*splits[path], left))) for left in (True, False)))  # noqa: B023

        trees.append(grown(()))
    return start, trees


def threshold(scored: list[tuple[float, float, float]], precision: float) -> float | None:
    """Least score such that the proposals from it up are positive at that rate, at every score above too; (score, positives, negatives)."""
    return threshold_of(sorted(scored, reverse=True), precision)


def threshold_of(ordered: Iterable[tuple[float, float, float]], precision: float) -> float | None:
    """:func:`threshold` of what comes in falling order of its score."""
    cut, pos, neg = None, 0.0, 0.0
    for s, p, n in ordered:
        pos, neg = pos + p, neg + n
        if (pos + 0.5) / (pos + neg + 1) < precision:
            if pos + neg > 20:
                break
        else:
            cut = s
    return cut


@dataclass(frozen=True)
class Model:
    kind: str
    start: float
    trees: list[Tree]
    cut: float

    def score(self, value) -> Column:
        return score_of(self.start, self.trees, value)


def seen_by(kind: str) -> tuple[str, ...]:
    """The features that a kind's trees see."""
    return tuple(f for f in FEATURES if f not in DEMANDED[kind] and f != f"hint_{kind}")


def fit_large(cells: DataFrame, *, precision: float) -> list[Model]:
    """:func:`fit` where the cells stay a table."""
    models = []
    for kind in KINDS:
        negative = F.when(F.col(f"hint_{kind}") == 1, 0.0).otherwise(F.col("n") - F.col(kind))
        mine = cells.where(F.col("g") == (0 if kind == "email" else 1)).select("half", *FEATURES, F.col(kind).cast("double").alias("pos"), negative.cast("double").alias("neg"))
        fitted = fit_table(mine.where("half"), names=seen_by(kind))
        if fitted is None:
            continue
        scored = mine.where("not half").groupBy(score_of(*fitted, F.col).alias("s")).agg(F.sum("pos").alias("p"), F.sum("neg").alias("n")).orderBy(F.desc("s"))
        cut = threshold_of((tuple(r) for r in scored.toLocalIterator()), precision)
        if cut is not None:
            models.append(Model(kind, *fitted, cut))
    return models


def fit(found: DataFrame, *, precision: float = 0.95) -> list[Model]:
    """Models of the kinds that have both positives and negatives; ``found`` is the written table of :func:`scan`."""
    each = found.select("half", F.explode("proposals").alias("x"))
    wanted = [F.sum(F.col(f"x.is_{k}").cast("long")).alias(k) for k in KINDS]
    cells = each.groupBy("half", "x.g", *[F.col(f"x.{f}").alias(f) for f in FEATURES]).agg(F.count("*").alias("n"), *wanted)
    cells = written(cells, "cells")
    if not small_enough(cells, MOST_CELLS):
        return fit_large(cells, precision=precision)
    cells = cells.orderBy(F.desc("n"), "half", "g", *FEATURES).collect()  # MOST_CELLS rows
    models = []
    for kind in KINDS:
        rows = [r for r in cells if r["g"] == (0 if kind == "email" else 1)]
        part = lambda half: [({f: r[f] for f in FEATURES}, float(r[kind]), 0.0 if r[f"hint_{kind}"] else float(r["n"] - r[kind])) for r in rows if r["half"] == half]  # noqa: B023, E731
        train = part(True)
        if not sum(c[1] for c in train) or not sum(c[2] for c in train):
            continue
        start, trees = fit_trees(train, names=seen_by(kind))
        cut = threshold([(start + sum(t.of(c[0]) for t in trees), c[1], c[2]) for c in part(False)], precision)
        if cut is not None:
            models.append(Model(kind, start, trees, cut))
    return models


def scan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, half, base, proposals): half says by a hash of the text whether trees are fitted to it or calibrated on it, base is a struct of span arrays by kind; proposals carry features and what base kind they meet."""
    text = F.col("text")
    found = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")).select("doc_id", "text", (F.pmod(F.xxhash64("text"), F.lit(2)) == 0).alias("half"), *[base_spans(text, k).alias(k) for k in KINDS], proposals(text).alias("p"))
    described = F.transform("p", lambda x: F.struct(x["g"].alias("g"), x["s"].alias("s"), x["e"].alias("e"), *[v.cast("int").alias(f) for f, v in zip(FEATURES, features(text, x), strict=True)], *[meets(x, F.col(k)).alias(f"is_{k}") for k in KINDS]))
    bare = lambda k: F.transform(k, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"))).alias(k)
    return found.select("doc_id", "half", F.struct(*[bare(k) for k in KINDS]).alias("base"), described.alias("proposals"))


def ranked(spans: Column, kind: str) -> Column:
    """array<struct<k,s,e>> of one kind's spans."""
    return F.transform(spans, lambda x: F.struct(F.lit(KINDS.index(kind)).alias("k"), x["s"].alias("s"), x["e"].alias("e")))


def added(models: list[Model]) -> Column:
    """array<struct<k,s,e>> of the proposals that a model adds; k is the kind's place in the list."""
    none = F.array().cast("array<struct<k:int,s:int,e:int>>")
    out = none
    for m in models:
        g = 0 if m.kind == "email" else 1
        new = F.filter("proposals", lambda x: (x["g"] == g) & ~(x["is_email"] | x["is_ip"] | x["is_card"] | x["is_phone"]) & (x[f"hint_{m.kind}"] == 1) & (m.score(lambda f: x[f]) >= m.cut))  # noqa: B023
        out = F.concat(out, ranked(new, m.kind))
    return out


def spelled(spans: Column) -> Column:
    """kind:start:end of array<struct<k,s,e>>, in order, comma-joined."""
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.concat_ws(",", F.transform(F.array_sort(F.array_distinct(spans)), lambda x: F.concat_ws(":", F.get(names, x["k"]), x["s"].cast("string"), x["e"].cast("string"))))


def personal_data(docs: DataFrame, *, precision: float = 0.95, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_<kind>, base_sha256, spans): counts of base spans, digest of their list, and the list of all spans.

    Places are code points, ends exclusive.  A null text is empty; one row an input row.
    """
    found = written(scan(docs, id_col=id_col, text_col=text_col), "personal")
    tagged = F.concat(*[ranked(F.col(f"base.{k}"), k) for k in KINDS])
    models = fit(found, precision=precision)
    listed = found.select("doc_id", "base", tagged.alias("b"), added(models).alias("a"))
    return listed.select("doc_id", *[F.size(f"base.{k}").cast("long").alias(f"n_{k}") for k in KINDS], F.sha2(spelled(F.col("b")), 256).alias("base_sha256"), spelled(F.concat("b", "a")).alias("spans"))


def redact(docs: DataFrame, *, precision: float = 0.95, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with every span replaced by its kind in brackets; overlapping spans leave the first one's mark.

    Ids must be unique where their texts differ.
    """
    spans = personal_data(docs, precision=precision, id_col=id_col, text_col=text_col).select(F.col("doc_id").alias("__id"), F.col("spans").alias("__spans")).distinct()
    joined = docs.join(spans, F.col(id_col).eqNullSafe(F.col("__id")), "left")
    parts = F.transform(F.split("__spans", ","), lambda x: F.split(x, ":"))
    ordered = F.array_sort(F.transform(F.filter(parts, lambda p: F.size(p) == 3), lambda p: F.struct(p[1].cast("int").alias("s"), p[2].cast("int").alias("e"), p[0].alias("k"))))
    text = text_of(text_col)

    def step(state: Column, x: Column) -> Column:
        piece = F.when(x["s"] >= state["pos"], F.concat(F.substring(text, state["pos"] + 1, x["s"] - state["pos"]), F.lit("["), x["k"], F.lit("]"))).otherwise(F.lit(""))
        return F.struct(F.greatest(state["pos"], x["e"]).alias("pos"), F.concat(state["out"], piece).alias("out"))

    start = F.struct(F.lit(0).alias("pos"), F.lit("").alias("out"))
    made = F.aggregate(ordered, start, step, lambda z: F.concat(z["out"], F.substring(text, z["pos"] + 1, F.char_length(text))))
    return joined.withColumn(text_col, F.when(F.col(text_col).isNull(), None).otherwise(made)).drop("__id", "__spans")
