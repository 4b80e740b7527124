import hashlib
import random

from tests.llm.frames import ROWS, none, odd
from wsample.llm import lines
from wsample.llm.queries import QUERIES


def near(a, b):
    """Word edit distance at most one, by the table."""
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1] <= 1


def units(w):
    """The brute force's own rule: words from three on, else the characters of five or more."""
    if len(w) >= 3:
        return "words", w
    line = b" ".join(w).decode()
    return ("characters", tuple(line)) if len(line) >= 5 else None


def slow(docs):
    """id -> (kept text, lines, exact, near) for unique ids."""
    seen, first, out = [], {}, {}
    for key, text in sorted(docs, key=lambda x: (x[0] is None, x[0] or 0)):
        kept, full, exact, close = [], 0, 0, 0
        for line in (text or "").split("\n"):
            w = tuple(line.encode().split())
            if not w:
                kept.append(line)
                continue
            full += 1
            if w not in first:
                mine = units(w)
                before = [v for v in seen if mine and v and v[0] == mine[0] and abs(len(v[1]) - len(mine[1])) < 2]
                first[w] = any(near(v[1], mine[1]) for v in before)
                again = False
                seen.append(mine)
            else:
                again = True
            if first[w]:
                close += 1
            elif again:
                exact += 1
            else:
                kept.append(line)
        out[key] = ("\n".join(kept) if text is not None else None, full, exact, close)
    return out


def check(df, docs):
    want = slow(docs)
    rows = lines.dedup_lines(df).collect()
    assert {r.doc_id: (r.text, r.n_lines, r.n_exact, r.n_near) for r in rows} == want
    return want


def test_random_lines(spark):
    pick = random.Random(1)
    base = [[f"w{pick.randint(0, 400)}" for _ in range(pick.randint(6, 14))] for _ in range(12)]

    def line():
        w = list(pick.choice(base))
        for _ in range(pick.choice([0, 0, 1, 1, 2])):
            p, how = pick.randrange(len(w)), pick.random()
            w[p : p + (how < 0.7)] = [] if how < 0.3 else [f"n{pick.randint(0, 5)}"]
        return pick.choice([" ", "  "]).join(w)

    docs = [(i, "\n".join(line() for _ in range(pick.randint(0, 5)))) for i in range(80)]
    want = check(spark.createDataFrame(docs, "doc_id long, text string").repartition(5), docs)
    assert sum(x[3] for x in want.values()) > 20


def test_short_lines(spark):
    """One to eight words, against every pair by the table; edits of lines of one or two words are characters."""
    texts = ["a b c d e f g h", "a b c d e f g", "Anat with by of nteres atre are.", "Tolyoued with by of nteres atre are.", "one two three", "one two four", "five one two three", "Yes.", "No.", "page one", "page two", "No.", "six seven", "six sevem", "sx seven", "Ωmegas", "Ωmega", "1", "2", "12345", "1234", "6 789", "6789", "a b c"]
    want = check(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3), list(enumerate(texts)))
    assert [k for k, x in want.items() if x[3]] == [1, 3, 5, 6, 13, 14, 16] and [k for k, x in want.items() if x[2]] == [11]


def test_long_lines_and_words(spark):
    """Words and lines longer than the hash tables, and lines that differ in their last byte."""
    word, line = "ab" * 700, " ".join(f"w{i}" for i in range(3000))
    texts = [word, word[:-1] + "c", word + " x", line, line + " end", line.replace("w1500 ", ""), line.replace("w7 ", "w8 w8 "), word + " y z", word[:-1] + "d y z"]
    check(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(2), list(enumerate(texts)))


def test_clashing_names(spark):
    docs = spark.createDataFrame([(1, "a b c d", 5, 6, 7), (2, "a b c d", 5, 6, 7)], "doc_id long, text string, __gone int, __id int, n_lines int")
    got = sorted((r.doc_id, r["__gone"], r["__id"], r.n_lines, r.n_exact) for r in lines.dedup_lines(docs).collect())
    assert got == [(1, 5, 6, 1, 0), (2, 5, 6, 1, 1)]


def test_hot_lines(spark, monkeypatch):
    """Lines looked up in the broadcast table and the others give the same result."""
    docs = [(i, "same old line here\n" + f"line number {i % 7} of it all {i % 3}") for i in range(60)]
    monkeypatch.setattr(lines, "HOT", 0.1)
    check(spark.createDataFrame(docs, "doc_id long, text string").repartition(4), docs)


def test_odd(spark):
    docs = [(r[0], r[1]) for r in ROWS if r[0] != 7] + [(8, ROWS[6][1])]
    check(spark.createDataFrame(docs, "doc_id long, text string"), docs)
    done = lines.dedup_lines(odd(spark), keep_empty=False)
    assert done.columns[: len(odd(spark).columns)] == odd(spark).columns
    assert sorted((r.doc_id or 0) for r in done.collect()) == [0, 1, 2, 3, 4, 5, 6, 9, 10]  # both rows of id 7 repeat the lines of 6
    assert lines.dedup_lines(none(spark)).count() == 0


def test_query(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    want = slow(docs)
    got = {r.doc_id: (r.text_md5, r.n_lines, r.n_exact, r.n_near) for r in QUERIES["op1_line_dedup"](spark, sf).collect()}
    assert got == {k: (hashlib.md5((t or "").encode()).hexdigest(), *rest) for k, (t, *rest) in want.items()}


def test_one_edit():
    for a, b in (("a b c", "a b c"), ("a b c", "a x c"), ("a b c", "a b c d"), ("a a a a", "a a a"), ("abcde", "abcdef"), ("ab cd", "ab ce")):
        assert lines.are_near(a, b) and lines.are_near(b, a)
    for a, b in (("a b c d", "x b d e"), ("a b c", "b a c"), ("a b", "c"), ("a b c", "a b"), ("abcd", "abce"), ("abcdef", "abdcef")):
        assert not lines.are_near(a, b) and not lines.are_near(b, a)
