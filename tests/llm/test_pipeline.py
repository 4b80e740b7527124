import itertools

import numpy as np

import corpus_pipeline
from tests.llm.frames import ROWS, none, odd
from tests.llm.test_documents import slow_hits
from wsample.llm import quality
from wsample.llm.common import written
from wsample.llm.queries import QUERIES


def test_quality_query(spark, sf):
    sf = sf.replace("0.001", "0.01")
    rows = {r.doc_id: r for r in QUERIES["op8_quality"](spark, sf).collect()}
    labels = spark.read.parquet(f"{sf}/labels.parquet").collect()
    good = [rows[r.doc_id].keep for r in labels if r.quality == 1 and r.toxic == 0]
    bad = [rows[r.doc_id].keep for r in labels if r.quality == 0 or r.toxic == 1]
    assert sum(good) >= 0.97 * len(good) and sum(bad) <= 0.2 * len(bad)
    assert len(rows) == spark.read.parquet(f"{sf}/documents.parquet").count()


def test_quality_of_unseen_labels(spark, sf):
    """Fitted to half of the labelled rows and held against the other half."""
    sf = sf.replace("0.001", "0.1")
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    mine = "pmod(xxhash64(doc_id), 2) = 0"
    judged = quality.classify(docs, labels.where(mine)).select("doc_id", "keep", "p_good")
    rows = judged.join(labels.where(f"not ({mine})").selectExpr("doc_id", "quality = 1 and toxic = 0 AS good", "toxic"), "doc_id").where("good is not null").collect()
    good, bad, toxic = ([r.keep for r in rows if x(r)] for x in (lambda r: r.good, lambda r: not r.good, lambda r: r.toxic == 1))
    print(len(rows), len(good), sum(good) / len(good), len(bad), sum(bad) / len(bad), len(toxic), sum(toxic) / max(1, len(toxic)))
    assert len(rows) > 1500 and sum(good) >= 0.97 * len(good) and sum(bad) <= 0.2 * len(bad) and sum(toxic) <= 0.2 * len(toxic)


def test_quality_odd(spark):
    labels = spark.createDataFrame([(6, 1, 0), (7, 1, 0), (4, 0, 0), (3, None, 0), (None, 1, 0), (5, 0, 1)], "doc_id long, quality int, toxic int")
    judged = quality.classify(odd(spark), labels)
    assert judged.count() == len(ROWS) and judged.where("keep is null or p_good is null").count() == 0
    assert quality.classify(none(spark), labels).count() == 0
    assert quality.classify(odd(spark), labels.limit(0)).count() == len(ROWS)


def test_sites_shrink(spark):
    rows = [("a", "x", 0.9)] * 300 + [("b", "x", 0.2)] * 300 + [("c", "x", 0.0)] + [("a", "y", 0.1)] * 100 + [(None, None, 0.5)] * 4
    rows = [(h, p, v + 0.05 * (i % 2)) for i, (h, p, v) in enumerate(rows)]
    got = {(r.host, r.path): r for r in quality.site_rates(spark.createDataFrame(rows, "host string, path string, p_doc double")).collect()}
    assert len(got) == 5 and abs(got["b", "x"].host_rate - 0.225) < 0.02
    assert 0 < got["c", "x"].host_rate  # one document does not settle a host


def shingles(text, k=5):
    w = text.encode().lower().split()
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))}


def similar_pairs(texts, least=0.8):
    """All pairs (i, j) of places in a list of texts whose shingle sets have that Jaccard similarity."""
    ids, names = [], {}
    for t in texts:
        ids.append(np.array([names.setdefault(s, len(names)) for s in shingles(t)] if t.split() else [], np.int64))
    n, owner = np.array([len(x) for x in ids]), np.repeat(np.arange(len(ids)), [len(x) for x in ids])
    order = np.argsort(np.concatenate(ids), kind="stable")
    holders, upto = owner[order], np.concatenate([[0], np.cumsum(np.bincount(np.concatenate(ids), minlength=len(names)))])
    for i, own in enumerate(ids):
        both = np.bincount(np.concatenate([holders[upto[s] : upto[s + 1]] for s in own] or [np.zeros(0, np.int64)]), minlength=len(ids))
        for j in np.flatnonzero((both > 0) & (both >= least * (n + n[i] - both))).tolist():
            if j > i:
                yield i, j


def test_copies_of_all_pairs(spark, sf):
    """On 10,000 documents, the near-dedup stage keeps what all pairs at 0.8 leave, however far fingerprints are apart."""
    docs = spark.read.parquet(f"{sf.replace('0.001', '0.1')}/documents.parquet")
    rows = docs.select("doc_id", "text").orderBy("doc_id").collect()
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in similar_pairs([r.text for r in rows]):
        x, y = find(i), find(j)
        root[max(x, y)] = min(x, y)
    empty = [i for i, r in enumerate(rows) if not r.text.split()]
    want = {r.doc_id for i, r in enumerate(rows) if find(i) == i and i not in empty[1:]}
    assert {r.doc_id for r in corpus_pipeline.drop_copies(spark, docs, sf).collect()} == want


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, items = docs.columns, [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    for name, stage in corpus_pipeline.STAGES:
        before = {r.doc_id: r for r in docs.collect()}
        docs = written(stage(spark, docs, sf), name)
        if name == "packing":
            assert {r.doc_id for r in docs.collect()} == set(before)
            break
        after = {r.doc_id: r for r in docs.collect()}
        assert docs.columns == columns and set(after) <= set(before) and len(after) > 0.4 * len(before)
        if name == "near_dedup":
            s = {k: shingles(r.text) for k, r in before.items()}
            alike = lambda a, b: len(s[a] & s[b]) >= 0.8 * len(s[a] | s[b])  # noqa: E731, B023
            assert not any(alike(a, b) for a, b in itertools.combinations(after, 2))
            assert all(any(alike(a, b) for b in before if b != a) for a in set(before) - set(after))
        if name == "decontamination":
            assert {k for k, r in before.items() if not slow_hits(r.text, items)[-1]} == set(after)


def test_stages_on_odd_rows(spark, sf):
    """Empty tables are in each operator's own tests."""
    docs = odd(spark)
    for name, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, sf), name)
    docs.count()


def test_equal_rows_once(spark, sf):
    exact = corpus_pipeline.drop_copies(spark, odd(spark), sf).collect()
    assert sorted(r.doc_id or 0 for r in exact) == [0, 1, 4, 5, 6, 9, 10]
