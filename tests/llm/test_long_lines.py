import random

from test_lines_substrings import sha

from tilemine.llm import lines as L


def brute_long(rows, w, least):
    """Runs of w counted lines, and shorter ones of at least so many words."""
    seen, gone = set(), {i: set() for i, _ in rows}
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0])):
        parts = (t or "").split("\n")
        at = [p for p, x in enumerate(parts) if x.strip(" \t\n\r\x0b\x0c")]
        for n in range(1, w + 1):
            for s in range(len(at) - n + 1):
                key = tuple(parts[p] for p in at[s : s + n])
                if n < w and sum(len(x.encode().split()) for x in key) < least:
                    continue
                if key in seen:
                    gone[i].update(at[s : s + n])
                seen.add(key)
    return gone


def long_rows():
    r = random.Random(8)
    shared = [" ".join(f"w{j}{n}" for j in range(n)) for n in (1, 3, 4, 5, 6, 7, 9, 10, 14)]
    rows = []
    for i in range(60):
        lines = [r.choice([*shared, "", " \t", "  ".join(f"u{i}{j}" for j in range(12))]) for _ in range(r.choice([0, 1, 1, 2, 2, 3, 12]))]
        rows.append((i * 2, "\n".join(lines)))
    whole = " ".join(f"x{j}" for j in range(60))
    return rows + [(300, whole), (301, whole), (302, whole + "\n" + whole), (303, "one short line"), (304, "one short line"), (305, None), (306, ""), (None, "é " * 10), (307, "é " * 10)]


def test_long_lines_against_brute_force(docs, by_id):
    rows = long_rows()
    gone = brute_long(rows, 3, 10)
    want = []
    for i, t in rows:
        parts = (t or "").split("\n")
        want.append((i, len(parts) if t else 0, len(gone[i]), sha("\n".join(x for p, x in enumerate(parts) if p not in gone[i]))))
    got = by_id(L.report(docs(rows), long_words=10), "doc_id", "n_lines", "n_removed", "kept_sha256")
    assert got == sorted(want, key=lambda r: (r[0] is not None, r[0]))


def test_long_copies_of_short_documents_go(docs):
    one, pair = " ".join(f"a{i}" for i in range(60)), "a b c d e\nf g h i j"
    df = docs([(1, one), (2, one), (3, pair), (4, pair), (5, "a b c"), (6, "a b c"), (7, "new\n" + one)])
    assert {r.doc_id: r.text for r in L.deduplicate(df, long_words=10).collect()} == {1: one, 3: pair, 5: "a b c", 6: "a b c", 7: "new"}


def test_long_lines_use_no_python(docs):
    plan = L.report(docs([(1, "a")]), long_words=10)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan
