import hashlib
import itertools
import re
import zlib

import numpy as np
import pytest
import xxhash

from tests.llm.frames import ROWS, none, odd
from wsample.llm import avi, decontaminate, graph, langid, simhash
from wsample.llm.queries import QUERIES


def frame(spark, sf):
    d = spark.read.parquet(f"{sf}/documents.parquet").toPandas()
    return dict(zip(d.doc_id, d.text, strict=True)), dict(zip(d.doc_id, d.lang, strict=True))


def ascii_lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text)


def slow_fingerprint(text, k=3):
    w = re.findall(r"[^\x20\x09-\x0D]+", ascii_lower(text))
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + k]).encode(), seed=42) for i in range(max(1, len(w) - k + 1))] if w else []
    return sum((2 * sum(x >> j & 1 for x in h) > len(h)) << j for j in range(64))


def slow_components(fps, most):
    """id -> least id reachable over links of at most ``most`` bits."""
    ids = sorted(fps)
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if (fps[a] ^ fps[b]).bit_count() <= most:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


def test_simhash_query(spark, sf):
    texts, _ = frame(spark, sf)
    got = {r.doc_id: r for r in QUERIES["op2_simhash_duplicates"](spark, sf).collect()}
    fps = {i: slow_fingerprint(t) for i, t in texts.items()}
    assert {i: int(r.fingerprint, 16) for i, r in got.items()} == fps
    assert {i: r.component_id for i, r in got.items()} == slow_components(fps, 2)


def test_simhash_odd(spark):
    got = simhash.near_duplicates(odd(spark)).collect()
    assert len(got) == len(ROWS)
    by = {r.doc_id: r for r in got}
    assert {by[i].component_id for i in (1, 2, 3)} == {1} and by[2].fingerprint == "0" * 16
    assert by[7].component_id == 6
    assert simhash.near_duplicates(none(spark)).count() == 0


@pytest.mark.parametrize("most", [2, 5])
def test_links_in_dense_groups(spark, most, monkeypatch):
    """A crowd of close fingerprints, larger than a block, and scattered ones."""
    monkeypatch.setattr(simhash, "BLOCK", 64)
    rng = np.random.default_rng(most)
    base = int(rng.integers(0, 2**63))
    fps = {base ^ sum(1 << int(b) for b in rng.choice(20, rng.integers(0, 5), replace=False)) for _ in range(500)} | {int(x) for x in rng.integers(0, 2**63, 300)}
    rows = [(i, int(np.uint64(f).view(np.int64))) for i, f in enumerate(sorted(fps))]
    path = simhash.written(spark.createDataFrame(rows, "key long, fp long"), "nodes")
    edges = simhash.links(path, most)
    assert all((rows[r.a][1] ^ rows[r.b][1]).bit_count() == r.bits <= most for r in edges.collect())
    roots = {r.node: r.root for r in graph.components(edges, "a", "b").collect()}
    assert {i: roots.get(i, i) for i, _ in rows} == slow_components(dict(rows), most)


def test_thresholds_meet_the_principle():
    rng = np.random.default_rng(0)
    bits = rng.integers(0, 2, (500, 64)).astype(float)
    bits[:, 40:48] = bits[:, :8]  # correlated
    for most in range(7):
        parts = simhash.plan_parts(500, bits.T @ bits, most)
        used = sum(p.threshold + 1 for p in parts)
        assert used == most + 1 and np.bitwise_or.reduce([np.uint64(p.mask) for p in parts]) is not None
    groups = simhash.grouped_bits(500, bits.T @ bits, 4)
    assert sorted(sum(groups, [])) == list(range(64)) and any({0, 40} <= set(g) for g in groups)


def test_verified_similarity(spark):
    words = [f"w{i}" for i in range(200)]
    near = [*words[:100], "other", *words[101:]]
    half = words[:100] + [f"v{i}" for i in range(100)]
    df = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(half)), (4, " ".join(words))], "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(df, shingle=5, max_bits=12, min_similarity=0.8).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 4: 1}


def similar_components(texts, least=0.8, most=64, k=5):
    """id -> least id reachable over pairs of that Jaccard similarity and at most ``most`` bits, by all pairs."""
    cut = {i: ascii_lower(t).encode().split() for i, t in texts.items()}
    sets = {i: {tuple(w[j : j + k]) for j in range(max(1, len(w) - k + 1))} if w else set() for i, w in cut.items()}
    fps = {i: slow_fingerprint(t, k) for i, t in texts.items()}
    root = {i: i for i in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(sorted(texts), 2):
        if len(sets[i] & sets[j]) >= least * len(sets[i] | sets[j]) and (fps[i] ^ fps[j]).bit_count() <= most:
            x, y = find(i), find(j)
            root[max(x, y)] = min(x, y)
    return {i: find(i) for i in texts}


def family(rng, n, core, own, copies):
    """Texts with a long passage in common and an own rest, and copies of some with a few words changed."""
    word = lambda: f"w{rng.integers(0, 50_000)}"
    base = [word() for _ in range(core)]
    out = [[*base, *(word() for _ in range(own))] for _ in range(n)]
    for i in range(copies):
        near = list(out[i])
        for p in rng.choice(len(near), len(near) // 48, replace=False):
            near[p] = word()
        out.append(near)
    return {i: " ".join(out[j]) for i, j in enumerate(rng.permutation(len(out)).tolist())}


def test_copies_in_a_family_of_one_template(spark):
    """Most pairs are within 12 bits and no copies; those of copies must not be thinned out by them."""
    texts = family(np.random.default_rng(5), 60, 240, 55, 30)
    want = similar_components(texts, most=12)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(df, shingle=5, max_bits=12, min_similarity=0.8).collect()}
    assert got == want and 60 <= len(set(want.values())) < 90


def test_sketches_bound_what_sets_do_not_share():
    rng = np.random.default_rng(3)
    hashes = rng.integers(0, 2**64, 40_000, np.uint64)
    sets = [rng.choice(hashes[:most], n, replace=False) for n, most in ((0, 10), (1, 10), (40, 60), (300, 350), (510, 600), (520, 600), (4000, 4400), (4200, 4400), (20_000, 40_000))]
    made = [simhash.sketch_of(np.concatenate([x, x[:5]])) for x in sets]
    assert [n for n, _ in made] == [len(x) for x in sets] and max(len(b) for _, b in made) < 20_000
    for (x, (_, a)), (y, (_, b)) in itertools.product(zip(sets, made, strict=True), repeat=2):
        assert simhash.apart(a, b) <= len(np.setxor1d(x, y)) and (simhash.apart(a, b) == 0 or len(np.setxor1d(x, y)))
    few = np.arange(1000, dtype=np.uint64)  # one bucket holds them all
    assert simhash.sketch_of(few) == (1000, b"") and simhash.apart(b"", made[3][1]) == 0


def test_few_pairs_fetch_their_texts(spark, monkeypatch):
    """Every two of ten texts share a rare passage; only copies are compared by their texts."""
    passage = {p: [f"{'-'.join(map(str, p))}w{k}" for k in range(60)] for p in itertools.combinations(range(10), 2)}
    texts = {i: [w for p in passage if i in p for w in passage[p]] for i in range(10)}
    for i in range(3):
        texts[10 + i] = [*texts[i][:200], "other", *texts[i][201:]]
    texts, compared, plain = {i: " ".join(t) for i, t in texts.items()}, [], simhash.similar

    def counted(pairs, *args, **kw):
        compared.append(pairs.select("a", "b").distinct().count())
        return plain(pairs, *args, **kw)

    monkeypatch.setattr(simhash, "similar", counted)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string").repartition(3)
    got = {r.doc_id: r.component_id for r in simhash.near_duplicates(df, shingle=5, max_bits=None, min_similarity=0.8).collect()}
    assert got == similar_components(texts) == {i: i % 10 for i in texts}
    assert 3 <= sum(compared) <= 6, compared


def test_components_of_a_path(spark):
    df = spark.createDataFrame([(i, i + 1) for i in range(50)] + [(100, 100)], "a long, b long")
    assert {r.node: r.root for r in graph.components(df, "a", "b").collect()} == {i: 0 for i in range(1, 51)}


def test_language_query(spark, sf):
    _, langs = frame(spark, sf)
    rows = QUERIES["op3_language_id"](spark, sf).collect()
    assert {r.doc_id for r in rows} == set(langs)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r.score <= 1 for r in rows)
    out = [r for r in rows if r.held_out]
    assert sum(r.lang_pred == langs[r.doc_id] for r in out) >= 0.97 * len(out)


def test_language_odd(spark):
    docs = odd(spark)
    got = {r.doc_id: r for r in langid.identify(docs, langid.train(docs)).collect()}
    assert [got[i].lang_pred for i in (1, 2, 3)] == ["und"] * 3 and got[5].lang_pred == "en"
    assert langid.identify(none(spark), langid.train(none(spark))).count() == 0
    assert {r.lang_pred for r in langid.identify(docs, langid.train(none(spark))).collect()} == {"und"}


def slow_vector(text, dimensions, seed):
    """A text's bundle, gram by gram from its letters."""
    out = np.zeros(dimensions, np.int64)
    low = f" {text.lower()} "
    for i in range(len(low) - 2):
        points = [ord(c) if c.isalpha() else 0 for c in low[i : i + 3]]
        if any(points):
            a, b, c = (langid.letter_vector(p, dimensions, seed).astype(np.int64) for p in points)
            out += np.roll(a, 2) * np.roll(b, 1) * c
    return out


def test_linear_products_are_the_cosines(spark):
    """Profiles and predictions against bundles made gram by gram."""
    known = [(1, "the cat sat on the mat", "en"), (2, "der Hund lag auf dem Boden", "de"), (3, "кот сидел на окне", "ru"), (4, "η γάτα κάθισε εκεί", "el"), (5, "แมวนั่งบนเสื่อ", "th"), (6, "les chats étaient là", "fr"), (7, "the dog and the fish", "en")]
    asked = [(10, "the cat and the dog", None), (11, "на окне сидел кот", None), (12, "η γάτα εκεί", None), (13, "แมวบนเสื่อ", None), (14, "là étaient les chats œuvre", None), (15, "1 2 3", None)]
    docs = spark.createDataFrame(known, "doc_id long, text string, lang string").repartition(3)
    profiles = langid.train(docs, dimensions=512, seed=4)
    langs = sorted({x[2] for x in known})
    want = np.array([sum(slow_vector(t, 512, 4) for _, t, l in known if l == lang) for lang in langs], float)
    want /= np.linalg.norm(want, axis=1, keepdims=True)
    assert profiles.languages == langs and np.allclose(profiles.prototypes, want, atol=1e-6)
    got = {r.doc_id: (r.lang_pred, r.score) for r in langid.identify(spark.createDataFrame(asked, "doc_id long, text string, lang string"), profiles).collect()}
    for key, text, _ in asked[:-1]:
        dots = want @ slow_vector(text, 512, 4)
        assert got[key][0] == langs[int(dots.argmax())] and abs(got[key][1] - dots.max() / np.maximum(dots, 0).sum()) < 1e-4
    assert [got[k][0] for k in (11, 12, 13)] == ["ru", "el", "th"] and got[15] == ("und", 0.0)


def test_products_are_forgotten_and_made_again(monkeypatch):
    rng = np.random.default_rng(2)
    profiles = langid.Profiles(["a", "b"], rng.normal(size=(2, 64)).astype(np.float32), 1)
    codes = np.unique(rng.integers(1, 1 << 60, 300))
    want = langid.gram_vectors(codes, 64, 1).astype(np.float32) @ profiles.prototypes.T
    monkeypatch.setattr(langid, "REMEMBERED", 50)
    monkeypatch.setattr(langid, "AT_ONCE", 7)
    held = langid.Products(profiles)
    for lo, hi in ((0, 40), (20, 60), (0, 300), (100, 140)):
        assert np.allclose(held.of(codes[lo:hi]), want[lo:hi], atol=1e-4)


def test_long_texts_in_slices(monkeypatch):
    text = "Ab çd, " * 40
    whole = langid._grams([f" {text.lower()} "])[0]
    monkeypatch.setattr(langid, "SLICE", 50)
    parts = list(langid._slices(text))
    assert len(parts) > 1 and np.array_equal(np.sort(np.concatenate([langid._grams([p])[0] for p in parts]))[-200:], np.sort(whole)[-200:])


def slow_hits(text, items, span=10):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", ascii_lower(t or ""))
    w, hit, names = words(text), set(), set()
    for name, item in items:
        v = words(item)
        for i in range(max(1, len(v) - span + 1) if v else 0):
            x = v[i : i + span]
            for p in range(len(w) - len(x) + 1):
                if w[p : p + len(x)] == x:
                    hit |= set(range(p, p + len(x)))
                    names.add(str(name))
    return len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)


def as_tuple(r):
    return r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated


def test_decontamination_query(spark, sf):
    texts, _ = frame(spark, sf)
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    rows = QUERIES["op6_decontamination"](spark, sf).collect()
    assert any(r.contaminated for r in rows)
    for r in rows:
        if r.doc_id % 4 == 0 or r.contaminated:
            assert as_tuple(r) == slow_hits(texts[r.doc_id], items)


def test_decontamination_odd(spark):
    items = [(1, "Two, THREE four five"), (2, None), (3, ""), (4, "one two three four five six seven eight nine ten eleven same"), (5, "soup word soup word soup word soup word soup word soup"), (6, "été naïve ωmega"), (None, "same line here"), (7, "a"), (4, "Again and again, it")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    named = [x for x in items if x[0] is not None]
    for block in (decontaminate.BLOCK_BYTES, 60):
        rows = decontaminate.contamination(odd(spark), bench, block_bytes=block).collect()
        assert len(rows) == len(ROWS)
        texts = {r[0]: r[1] for r in ROWS}
        for r in rows:
            if r.doc_id != 5:
                assert as_tuple(r) == slow_hits(texts[r.doc_id], named)
            else:
                assert (r.n_hit, r.n_items) == (40_000, 1)
    kept = decontaminate.clean(odd(spark), bench)
    assert kept.columns == odd(spark).columns and {r.doc_id for r in kept.collect()} == {k for k, t in texts.items() if k != 5 and not slow_hits(t, named)[-1]}
    assert decontaminate.clean(none(spark), bench).count() == decontaminate.contamination(none(spark), bench).count() == 0
    assert decontaminate.clean(odd(spark), bench.limit(0)).count() == len(ROWS)


def test_every_long_shared_span_is_found():
    rng = np.random.default_rng(4)
    for _ in range(60):
        item, n, at = [f"x{i}" for i in rng.integers(0, 30, 40)], int(rng.integers(10, 15)), int(rng.integers(0, 25))
        text = [f"y{i}" for i in range(int(rng.integers(0, 9)))] + item[at : at + n] + [f"z{i}" for i in range(int(rng.integers(0, 9)))]
        index = decontaminate.Index(10, 5)
        index.add("i", " ".join(item))
        found = decontaminate.find(decontaminate.words_of([" ".join(text)]), index.close())[0]
        assert found[1] == {"i"}


def test_media_query(spark, sf):
    texts, _ = frame(spark, sf)
    for r in QUERIES["op9_motion_jpeg"](spark, sf).collect():
        raw = texts[r.doc_id].encode()
        data = raw + bytes(-len(raw) % 64)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(data), hashlib.sha256(data).hexdigest(), zlib.crc32(data[-64:]))


def test_media_odd(spark):
    media = avi.to_media(odd(spark))
    rows = {r.doc_id: r for r in avi.media_features(media).collect()}
    assert rows[1].payload_bytes == rows[2].payload_bytes == 64 and rows[1].media_sha256 == rows[2].media_sha256
    assert rows[6].feature == rows[7].feature
    cut = avi.clips(media).collect()
    assert {r.doc_id for r in cut} == {r[0] for r in ROWS} and all(r.end_s > r.start_s for r in cut)
    assert avi.media_features(avi.to_media(none(spark))).count() == avi.clips(avi.to_media(none(spark))).count() == 0


def test_media_clips_of_the_query(spark, sf):
    """The query's clips are the clip rows of the same files, and cover every frame once in order."""
    media = avi.to_media(spark.read.parquet(f"{sf}/documents.parquet"))
    rows = {}
    for r in sorted(avi.clips(media).collect(), key=lambda r: (r.doc_id, r.clip_no)):
        rows.setdefault(r.doc_id, []).append(f"{r.first_frame}:{r.n_frames}:{round(1000 * r.start_s)}:{round(1000 * r.end_s)}")
    for r in QUERIES["op9_motion_jpeg"](spark, sf).collect():
        assert r.clips.split(",") == rows[r.doc_id]
        spans = [tuple(map(int, x.split(":"))) for x in rows[r.doc_id]]
        assert [x[0] for x in spans] == [sum(x[1] for x in spans[:k]) for k in range(len(spans))]
        assert f"frames={sum(x[1] for x in spans)};shots={len(spans)};" in r.feature


def test_damaged_media(spark):
    whole = avi.write_avi(b"some text" + bytes(55))
    rng = np.random.default_rng(3)
    files = [whole, None, b"", b"RIFF", whole[:40], whole[: len(whole) // 2], b"not a movie at all", *(bytes(x ^ int(y) for x, y in zip(whole, rng.integers(0, 256, len(whole)) * (rng.random(len(whole)) < 0.05), strict=True)) for _ in range(60))]
    media = spark.createDataFrame([(i, 9, x) for i, x in enumerate(files)], "doc_id long, n_bytes long, media binary")
    rows = {r.doc_id: r for r in avi.media_features(media).collect()}
    assert len(rows) == len(files) and rows[0].payload_bytes == 64 and rows[1].media_bytes is None
    for i in range(2, 7):
        assert rows[i].media_bytes == len(files[i]) and rows[i].payload_sha256 is None and rows[i].clips is None
    assert {r.doc_id for r in avi.clips(media).collect()} == {i for i, r in rows.items() if r.clips}


def test_frames_round_trip_and_general_decoder():
    rng = np.random.default_rng(0)
    for n in (64, 4096, 64 * 65, 64 * 150):
        for data in (rng.integers(0, 256, n, dtype=np.uint8).tobytes(), bytes(n), b"\xff" * n, (b"\x00\xff" * n)[:n]):
            movie = avi.parse_avi(avi.write_avi(data))
            assert avi.payload_of(movie, avi.decode(movie)) == data
    image = rng.integers(0, 256, (1, 8, 64), dtype=np.uint8)
    found, scan = avi._segments(avi.encode_frames(image)[0])
    table = found[0xC4]
    assert np.array_equal(avi._bit_by_bit(scan, table[1:17], table[17:], 512).reshape(8, 64), avi._differences(image)[0])


def test_movie_without_index_and_shots():
    dark, light = np.zeros((64, 64), np.uint8), np.full((64, 64), 200, np.uint8)
    images = np.stack([dark] * 6 + [light] * 6)
    data = avi.write_avi(images.tobytes())
    bare = data[: data.rindex(b"idx1")]
    movie = avi.parse_avi(bare)
    assert movie.frames == avi.parse_avi(data).frames and avi.shot_starts(avi.decode(movie)) == [0, 6]
