import hashlib
import random

import numpy as np
import pytest

from tilemine.llm import lines as L, substrings as U


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def brute_lines(rows, w):
    counted = {i: [p for p, x in enumerate((t or "").split("\n")) if x.strip(" \t\n\r\x0b\x0c")] for i, t in rows}
    seen, gone = set(), {i: set() for i, _ in rows}
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0])):
        own = [(t or "").split("\n")[p] for p in counted[i]]
        for s in range(len(own) - w + 1):
            key = tuple(own[s : s + w])
            if key in seen:
                gone[i].update(counted[i][s : s + w])
            seen.add(key)
    return gone


def line_rows():
    r = random.Random(3)
    rows = []
    for i in range(60):
        lines = [r.choice(["a", "b", "c", "long line here", "", "  ", f"only {i}"]) for _ in range(r.choice([0, 1, 2, 5, 30]))]
        rows.append((i * 3, "\n".join(lines)))
    block = "first\nsecond\nthird\nfourth"
    return rows + [(500, block), (501, "x\n" + block + "\ny"), (502, "second\nthird\nfourth"), (503, None), (504, ""), (None, block), (505, "r\nr\nr\nr\nr\nr")]


@pytest.mark.parametrize("w", [1, 2, 3])
def test_lines_against_brute_force(docs, by_id, w):
    rows = line_rows()
    gone = brute_lines(rows, w)
    want = []
    for i, t in rows:
        parts = (t or "").split("\n")
        want.append((i, len(parts) if t else 0, len(gone[i]), sha("\n".join(x for p, x in enumerate(parts) if p not in gone[i]))))
    got = by_id(L.report(docs(rows), w), "doc_id", "n_lines", "n_removed", "kept_sha256")
    assert got == sorted(want, key=lambda r: (r[0] is not None, r[0]))


def test_lines_deduplicate_keeps_columns_and_clean_rows(docs):
    df = docs([(1, "a\nb\nc\nd"), (2, "a\nb\nc"), (3, "z\na\nb\nc\n"), (4, None), (5, "")])
    out = {r.doc_id: r for r in L.deduplicate(df).collect()}
    assert L.deduplicate(df).columns == df.columns
    assert sorted(out) == [1, 3, 4, 5] and out[3].text == "z\n" and out[3].n_chars == 2 and out[1].text == "a\nb\nc\nd" and out[4].text is None
    assert L.deduplicate(docs([])).count() == 0


def test_lines_repeated_rows_are_one_document(docs):
    df = docs([(1, "a\nb\nc"), (1, "a\nb\nc")])
    assert [r.n_removed for r in L.report(df).collect()] == [0, 0]


def test_rows_of_one_id_lose_only_what_stands_earlier(docs):
    """What is found in a row is deleted in it alone; rows of one id are none earlier than the other."""
    df = docs([(1, "a\nb\nc"), (5, "a\nb\nc\nz"), (5, "p\nq\nr\ns"), (5, "p\nq\nr\ns"), (None, "p\nq\nr\nt"), (6, "z\np\nq\nr")])
    assert sorted(r.text for r in L.deduplicate(df).collect()) == sorted(["a\nb\nc", "z", "s", "s", "p\nq\nr\nt", "z"])
    df = docs([(1, "a\nb\nc"), (5, "a\nb\nc\nz"), (5, "p\nq\nr\ns")])
    assert sorted(r.text for r in L.deduplicate(df).collect()) == ["a\nb\nc", "p\nq\nr\ns", "z"]


def test_lines_with_clashing_columns(spark):
    names = "__text __k __key __lines __gone __places __runs row runs lines gone places counted within left t k fp at start n key again first".split()
    df = spark.createDataFrame([(i, t, *[f"{c}{i}" for c in names]) for i, t in ((1, "a\nb\nc\nd"), (2, "x\na\nb\nc"))], "doc_id long, text string, " + ", ".join(f"`{c}` string" for c in names))
    out = {r.doc_id: r for r in L.deduplicate(df).collect()}
    assert out[2].text == "x" and out[1].text == "a\nb\nc\nd" and all(out[i][c] == f"{c}{i}" for i in out for c in names)
    assert L.deduplicate(df).columns == df.columns and L.report(df).count() == 2


def test_matches_extend_both_ways_from_their_fingerprint(docs):
    shared = "\n".join(f"line {i}" for i in range(40))
    df = docs([(1, "head\n" + shared), (2, "one\ntwo\n" + shared + "\nthree"), (3, "\n".join(shared.split("\n")[7:29]))])
    assert sorted((r.doc_id, r.text) for r in L.deduplicate(df).collect()) == [(1, "head\n" + shared), (2, "one\ntwo\nthree")]
    runs = {r.k: sorted((x["from"], x["to"]) for x in r.runs) for r in L.repeated(df).collect()}
    assert set(runs) == {2, 3} and min(a for a, _ in runs[2]) == 2 and max(b for _, b in runs[2]) == 42
    assert any(b - a > L.WINDOW for a, b in runs[2]) and all(b - a <= 2 * L.WINDOW - 1 for a, b in runs[2])


def test_a_very_long_text(docs):
    lines = [f"l{i}" for i in range(200_000)]
    got = L.report(docs([(1, "\n".join(lines)), (2, "\n".join(lines[50_000:150_000]) + "\nend")]))
    assert sorted((r.doc_id, r.n_lines, r.n_removed) for r in got.collect()) == [(1, 200_000, 0), (2, 100_001, 100_000)]


def test_lines_use_no_python(docs):
    plan = L.report(docs([(1, "a")]))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def brute_words(rows, w):
    out = {}
    seen = set()
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0])):
        ws, gone = (t or "").encode().split(), set()
        for s in range(len(ws) - w + 1):
            key = tuple(ws[s : s + w])
            if key in seen:
                gone.update(range(s, s + w))
            seen.add(key)
        out[i] = (len(ws), len(gone), hashlib.sha256(b" ".join(x for p, x in enumerate(ws) if p not in gone)).hexdigest())
    return out


def word_rows():
    r = random.Random(4)
    shared = [[f"s{r.randrange(50)}" for _ in range(n)] for n in (6, 9, 25, 60)]
    rows = []
    for i in range(70):
        ws = []
        for _ in range(r.choice([0, 1, 3])):
            ws += [f"u{r.randrange(40)}" for _ in range(r.choice([0, 2, 12]))]
            part = r.choice(shared)
            cut = r.randrange(len(part))
            ws += part[cut:] if r.random() < 0.5 else part[: cut + 1]
        rows.append((i * 2, " ".join(ws)))
    return rows + [(900, None), (901, ""), (902, "é " * 40), (903, "x y " * 30), (None, " ".join(shared[3])), (904, " ".join(shared[3]) + "\n\ttail")]


@pytest.mark.parametrize("w,k", [(6, 3), (8, 8), (20, 8)])
def test_substrings_against_brute_force(docs, by_id, w, k):
    rows = word_rows()
    want = brute_words(rows, w)
    got = {r[0]: r[1:] for r in by_id(U.deduplicate(docs(rows), w, k), "doc_id", "n_words", "n_removed", "kept_sha256")}
    assert got == want
    assert sum(x[1] for x in want.values()) > 0


def test_substrings_edges(docs):
    assert U.deduplicate(docs([])).count() == 0
    same = " ".join(f"w{i}" for i in range(30))
    assert [r.n_removed for r in U.deduplicate(docs([(1, same), (1, same)])).collect()] == [0, 0]
    assert sorted((r.doc_id, r.kept) for r in U.deduplicate(docs([(1, same), (2, "a " + same)])).collect()) == [(1, same), (2, "a")]


def test_sliding_minimum():
    x = np.random.default_rng(0).integers(0, 1000, 50)
    for w in (1, 2, 5, 13):
        assert U._least(x, w).tolist() == [min(x[i : i + w]) for i in range(50 - w + 1)]
