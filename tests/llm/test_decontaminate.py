import hashlib
import random
import re

import numpy as np
import pytest

from tilemine.llm import decontaminate as D

WORD = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def fold(text):
    return WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))


def brute(text, items, window=13):
    ws = fold(text)
    hit, found = set(), set()
    for name, body in items:
        item = fold(body)
        n = min(window, len(item))
        for i in range(len(item) - n + 1 if n else 0):
            for j in range(len(ws) - n + 1):
                if ws[j : j + n] == item[i : i + n]:
                    hit.update(range(j, j + n))
                    found.add(str(name))
    return len(ws), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(ws)


def cases():
    r = random.Random(5)
    vocabulary = ["a", "b", "c", "D", "é", "x1"]
    items = [(i, " ".join(r.choices(vocabulary, k=r.choice([0, 1, 2, 5, 13, 14, 30])))) for i in range(12)] + [(99, None), (3, "q w e r t")]
    texts = [" ".join(r.choices(vocabulary, k=r.choice([0, 3, 20, 80]))) for _ in range(30)] + [None, "", "!!", "Q,w;E\nr\tT", items[6][1]]
    texts += [(items[j][1] or "") + " tail " + (items[j + 1][1] or "") for j in range(10)]
    return items, texts


@pytest.mark.parametrize("block", [3, 10_000])
def test_against_brute_force(spark, docs, by_id, block):
    items, texts = cases()
    items = items[:3] + items[5:]
    frame = docs(list(enumerate(texts)))
    bench = spark.createDataFrame(items, "item_id long, text string")
    out = D.hits(frame, bench, window=5, block_words=block)
    got = by_id(out, "doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
    assert got == [(i, *brute(t, items, 5)) for i, t in enumerate(texts)]


def test_clean_cuts_spans_and_drops_documents(spark, docs):
    bench = spark.createDataFrame([(1, " ".join(f"w{i}" for i in range(13)))], "item_id long, text string")
    passage = " ".join(f"W{i}," for i in range(13))
    long = " ".join(f"z{i}" for i in range(400))
    rows = {r.doc_id: r for r in D.clean(docs([(1, passage), (2, f"{long} {passage} end."), (3, "  Untouched;\n text "), (4, None), (5, passage[:-9])]), bench).collect()}
    assert sorted(rows) == [2, 3, 4, 5]
    assert rows[2].text == f"{long} end." and rows[2].n_chars == len(rows[2].text)
    assert rows[3].text == "  Untouched;\n text " and rows[4].text is None and rows[5].text == passage[:-9]


def test_many_blocks_and_a_million_item_words(spark, docs):
    """Blocks are built in tasks and read in turn; their bytes are measured, and the result is that of one block."""
    items = [(i, " ".join(f"w{(i * 7919 + j * j) % 50_021}" for j in range(500))) for i in range(2000)]
    bench = spark.createDataFrame(items, "item_id long, text string")
    folder, files = D.build(bench, 13)
    assert len(files) >= 8 and max(n for _, n in files) < 16 << 20 and sum(n for _, n in files) < 100 * 1_000_000
    texts = [items[5][1], "x " + " ".join(items[77][1].split()[100:120]) + " y", " ".join(f"w{j}" for j in range(300)), " ".join(items[1999][1].split()[:12]), None]
    got = [(r.doc_id, r.n_hit, r.items) for r in D.hits(docs(list(enumerate(texts))), bench).orderBy("doc_id").collect()]
    assert got[0][1] == 500 and "5" in got[0][2] and got[1][1:] == (20, ["77"]) and [g[1] for g in got[3:]] == [0, 0]


def test_null_and_empty_item_ids_differ(spark, docs):
    words = " ".join(f"w{i}" for i in range(13))
    bench = spark.createDataFrame([(None, words), ("", words), ("a", words), ("a", "other words")], "item_id string, text string")
    r = D.hits(docs([(1, words)]), bench).first()
    assert (r.n_items, r.items) == (3, [None, "", "a"]) and r.items_sha256 == hashlib.sha256(b",a").hexdigest()


def test_a_very_long_text_among_others(spark, docs):
    words = " ".join(f"w{i}" for i in range(13))
    bench = spark.createDataFrame([(1, words)], "item_id long, text string")
    long = " ".join(f"z{i}" for i in range(400_000)) + " " + words
    got = [(r.doc_id, r.n_words, r.n_hit, r.contaminated) for r in D.hits(docs([(1, long), (2, words), (3, "")]), bench).orderBy("doc_id").collect()]
    assert got == [(1, 400_013, 13, False), (2, 13, 13, True), (3, 0, 0, False)]
    assert list(D.slices([5, 5, 20, 1, 1], 10)) == [(0, 2), (2, 3), (3, 5)]


def test_empty_tables(spark, docs):
    bench = spark.createDataFrame([], "item_id long, text string")
    assert D.hits(docs([]), bench).count() == 0
    assert [r.n_hit for r in D.hits(docs([(1, "a b")]), bench).collect()] == [0]
    assert D.clean(docs([(1, "a b")]), bench).count() == 1


def test_hits_mark_words():
    a = D.Automaton.of([("1", b"a b c d".split()), ("2", b"c d".split())], 3)
    hit = np.zeros(7, bool)
    assert a.scan(b"x a b c d c d".split(), hit) == {"1", "2"}
    assert hit.tolist() == [False, True, True, True, True, True, True]
