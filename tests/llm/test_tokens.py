import random
import zlib
from collections import defaultdict

import numpy as np
import public_tokenizers
from tokenizers import Tokenizer

from tests.llm.frames import ROWS, none, odd
from wsample.llm import packing, store, tokens
from wsample.llm.queries import QUERIES

BYTE, WORD = (public_tokenizers.path(x) for x in ("byte_bpe_50k.json", "word_bpe_49k.json"))


def ids_of(path, text):
    return Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids


def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").toPandas()


def test_pieces_agree_with_the_libraries():
    odd_texts = [r[1] or "" for r in ROWS[:1] + ROWS[5:]] + [" a", "a ", "a  b", "a\n\nb", "a \nb", "a\n b", "\n", "İstanbul ΣΑΣ", "é", "a\x1cb", "it's WE'VE", "²³ ½x", "<|startoftext|>x"]
    pick = random.Random(3)
    odd_texts += ["".join(pick.choices(" \n\t ab'sé<>|日²\x1c\xa0İΣ1.,", k=pick.randint(0, 12))) for _ in range(1500)]
    libraries = {p: Tokenizer.from_file(p) for p in (BYTE, WORD)}
    for text in odd_texts:
        for kind, path in (("byte", BYTE), ("word", WORD), ("count", WORD)):
            want = libraries[path].encode(text, add_special_tokens=False).ids
            got = tokens.encoder(kind, path)(text)
            assert got == (len(want) if kind == "count" else np.array(want, dtype="<u4").tobytes()), (kind, text)


def test_every_character_below_250_and_marks():
    """Every code point that the fast rules may see, alone and among others, and those whose lower case is beyond them."""
    library = Tokenizer.from_file(WORD)
    ids, count = tokens.encoder("word", WORD), tokens.encoder("count", WORD)
    points = [chr(c) for c in [*range(1, 0x250), *range(0x300, 0x370)]]
    moved = [c for c in points if any(ord(x) > 0x24F for x in c.lower())]
    pick = random.Random(9)
    texts = [f(c) for c in points for f in (lambda c: c, lambda c: f"ab{c}cd {c}{c}", lambda c: f"{c}'s 1{c}2", lambda c: f"e{c}\u0301 {c}")]
    texts += ["".join(pick.choice([*moved, pick.choice(points), "a", "e", " ", "'s", "1"]) for _ in range(pick.randint(1, 14))) for _ in range(4000)]
    assert len(moved) >= 23
    for text in texts:
        want = library.encode(text, add_special_tokens=False).ids
        assert np.frombuffer(ids(text), "<u4").tolist() == want and count(text) == len(want), repr(text)


def test_merges_stop_where_ranks_end():
    rank = {("a", "b"): 0, ("ab", "c"): 1, ("b", "c"): 2}
    assert tokens.count_after_merges(list("abc"), rank) == 1
    assert tokens.count_after_merges(list("bcab"), rank) == 2
    assert tokens.count_after_merges([], rank) == 0


def test_counts_query(spark, sf):
    library = Tokenizer.from_file(WORD)
    docs = {r.doc_id: r.text for r in documents(spark, sf).itertuples()}
    for r in QUERIES["op7_token_counts"](spark, sf).collect():
        n = len(library.encode(docs[r.doc_id], add_special_tokens=False).ids)
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(docs[r.doc_id].encode()), n, n > 2048)


def test_store_query(spark, sf):
    library, start = Tokenizer.from_file(WORD), 0
    got = {r.doc_id: r for r in QUERIES["op5_token_store"](spark, sf).collect()}
    for r in documents(spark, sf).sort_values("doc_id").itertuples():
        ids = library.encode(r.text, add_special_tokens=False).ids + [1]
        assert (got[r.doc_id].start, got[r.doc_id].n_tokens, got[r.doc_id].ids_crc32, got[r.doc_id].verified) == (start, len(ids), zlib.crc32(np.array(ids, dtype="<u4").tobytes()), True)
        start += len(ids)


def test_store_round_trip_and_damage(spark):
    made = store.write_store(odd(spark), WORD)
    assert made.chunks.groupBy("digest").count().where("count > 1").count() == 0
    ids = defaultdict(list)
    for r in store.reconstruct(made).collect():
        ids[r.doc_id].append(r.ids)
    for r in ROWS:
        assert ids_of(WORD, r[1] or "") + [1] in ids[r[0]]
    assert sum(map(len, ids.values())) == len(ROWS)
    lost = store.Store(made.chunks.where("n_ids <> 1"), made.recipes, made.manifest, made.path)
    assert {r.doc_id for r in store.read_documents(lost).where("not verified").collect()} == {1, 2, 3}
    assert store.read_documents(store.write_store(none(spark), WORD)).count() == 0


def test_chunks_follow_content():
    rng = np.random.default_rng(1)
    a = rng.integers(0, 40_000, 20_000).astype("<u4")
    b = np.concatenate([a[:5000], rng.integers(0, 40_000, 37).astype("<u4"), a[5000:]])
    parts = [{x[i:j].tobytes() for i, j in zip([0, *store.cuts(x)], store.cuts(x), strict=False)} for x in (a, b)]
    assert len(parts[0] & parts[1]) > 0.9 * len(parts[0])
    assert max(np.diff([0, *store.cuts(a)])) <= store.MOST


def test_crc_join():
    a, b = b"first bytes", b"second" * 99
    assert store.join_crc(zlib.crc32(a), zlib.crc32(b), len(b)) == zlib.crc32(a + b)


def check_packing(rows, texts, capacity):
    bins, docs = defaultdict(list), defaultdict(list)
    for r in rows:
        bins[r.sequence_id].append((r.offset, r.length))
        docs[r.doc_id].append(r)
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    library = Tokenizer.from_file(BYTE)
    for key, text in texts:
        ids = library.encode(text or "", add_special_tokens=False).ids + [2]
        pieces = sorted(docs[key], key=lambda r: r.piece)
        n = texts.count((key, text))
        assert sum(r.length for r in pieces) == n * len(ids)
        for r in pieces:
            assert r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], dtype="<u4").tobytes())
            assert r.length == capacity or r.piece == 0
    return len(bins), -(-sum(r.length for r in rows) // capacity)


def test_pack_query(spark, sf):
    docs = documents(spark, sf)
    used, least = check_packing(QUERIES["op4_pack_sequences"](spark, sf).collect(), list(zip(docs.doc_id, docs.text, strict=True)), 1024)
    assert used <= 1.02 * least + 2


def test_pack_odd(spark):
    check_packing(packing.pack_documents(odd(spark), BYTE, capacity=64).collect(), [(r[0], r[1]) for r in ROWS], 64)
    assert packing.pack_documents(none(spark), BYTE).count() == 0


def test_runs_are_bounded_and_ranks_whole(spark, monkeypatch):
    """Many small runs of one hot length give every piece a place of its own, and runs stay few however many pieces there are."""
    monkeypatch.setattr(packing, "RUN_PIECES", 7)
    pieces = spark.range(500).selectExpr("id AS doc_id", "0 AS piece", "0L AS start", "if(id % 3 = 0, 5L, 64L) AS length", "id AS ids_crc32")
    rows = packing.pack(pieces, capacity=64).collect()
    assert len({(r.sequence_id, r.offset) for r in rows}) == len({r.doc_id for r in rows}) == 500
    assert len({r.sequence_id for r in rows}) == 333 + -(-167 // 12)
    runs = packing.runs_of({1024: 25 * 10**9, 3: 1, 7: 10**6})
    assert runs[3] == 1 and sum(runs.values()) <= packing.MOST_RUNS + 3


def test_fullest_is_optimal():
    pick = random.Random(5)
    for _ in range(200):
        counts = {pick.randint(1, 20): pick.randint(1, 3) for _ in range(pick.randint(1, 5))}
        room = pick.randint(0, 40)
        sums = {0}
        for length, n in counts.items():
            sums = {s + k * length for s in sums for k in range(n + 1) if s + k * length <= room}
        got = packing.fullest(counts, room)
        assert sum(length * k for length, k in got) == max(sums) and all(k <= counts[length] for length, k in got)
