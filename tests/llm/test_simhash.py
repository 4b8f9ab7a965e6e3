import random

import numpy as np
import pytest
import xxhash

from tilemine.llm import simhash as S


def brute(text):
    words = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").encode().split()
    if not words:
        return 0
    n = max(1, len(words) - 2)
    hs = [xxhash.xxh64_intdigest(b" ".join(words[i : i + 3]), 42) for i in range(n)]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > n)


def classes(fps):
    """Smallest id reachable, by comparing all pairs."""
    parent = list(range(len(fps)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, (_, a) in enumerate(fps):
        for j, (_, b) in enumerate(fps[:i]):
            if (a ^ b).bit_count() <= 3:
                parent[root(i)] = root(j)
    least = {}
    for i, (k, _) in enumerate(fps):
        r = root(i)
        least[r] = k if r not in least else min(least[r], k, key=lambda x: (x is not None, x))
    return [least[root(i)] for i in range(len(fps))]


def near_texts():
    r = random.Random(2)
    base = [[f"w{r.randrange(300)}" for _ in range(r.choice([3, 40, 300]))] for _ in range(25)]
    texts = []
    for words in base:
        for _ in range(r.choice([1, 1, 4, 9])):
            copy = list(words)
            for _ in range(r.choice([0, 1, 2])):
                copy[r.randrange(len(copy))] = f"x{r.randrange(9)}"
            texts.append(" ".join(copy))
    return texts + [None, "", " \n", "One two", "one TWO", "one"]


def test_fingerprints_and_components(docs, by_id):
    rows = [(i * 7 + 1, t) for i, t in enumerate(near_texts())] + [(None, "one"), (8, near_texts()[1])]
    got = by_id(S.near_duplicates(docs(rows)), "doc_id", "fingerprint", "component_id")
    fps = [(i, brute(t)) for i, t in rows]
    want = sorted(((i, f"{f:016x}", c) for (i, f), c in zip(fps, classes(fps))), key=lambda r: tuple((x is not None, x) for x in r))
    assert got == want


def test_stretches_of_a_long_text_make_one_fingerprint(monkeypatch):
    whole = [S.fingerprint((t or "").encode()) for t in near_texts()]
    assert whole == [brute(t) for t in near_texts()]
    plain = S.word_lists
    monkeypatch.setattr(S, "word_lists", lambda body: plain(body, 7))
    assert [S.fingerprint((t or "").encode()) for t in near_texts()] == whole


def test_hot_groups_are_cut_without_losing_links(docs, by_id):
    rows = [(i, t) for i, t in enumerate(near_texts())]
    df = docs(rows)
    assert by_id(S.near_duplicates(df, most=2), "doc_id", "component_id") == by_id(S.near_duplicates(df), "doc_id", "component_id")


@pytest.mark.parametrize("blocks", [4, 5, 6, 7])
def test_every_choice_of_blocks_finds_all_links(spark, blocks):
    r = np.random.default_rng(blocks)
    centre = r.integers(0, 2**64, 40, dtype=np.uint64)
    flips = [np.bitwise_xor.reduce(np.uint64(1) << r.choice(64, k, replace=False).astype(np.uint64)) for k in (1, 2, 3, 3, 4)]
    codes = np.unique(np.concatenate([centre, *[centre ^ f for f in flips], r.integers(0, 2**64, 300, dtype=np.uint64)]))
    frame = spark.createDataFrame([(int(x),) for x in codes.view(np.int64)], "fp long")
    got = {x.node: x.root for x in S.components(S.links(frame, blocks=blocks)).collect()}
    signed = {int(x): int(x) - (int(x) >> 63 << 64) for x in codes}
    want = dict(zip(signed.values(), classes([(signed[int(x)], int(x)) for x in codes])))
    assert {k: v for k, v in want.items() if k != v or k in got} == got and len(got) > 100


def test_masks_and_their_number():
    assert [len(S.masks(b, 3)) for b in (4, 5, 6)] == [4, 10, 20] and sum(S.masks(4, 3)) == -1
    assert all((m & 0xFFFFFFFFFFFFFFFF).bit_count() in (25, 26) for m in S.masks(5, 3))
    assert [S.block_count(n, 3) for n in (0, 10**5, 10**6, 10**8, 10**10)] == [4, 4, 4, 5, 6]


def test_a_long_text_and_clashing_columns(docs, by_id):
    long = " ".join(f"w{i}" for i in range(200_000))
    got = by_id(S.near_duplicates(docs([(7, long), (3, long + " end"), (5, "other words here now")])), "doc_id", "component_id")
    assert got == [(3, 3), (5, 5), (7, 3)]


def test_index_finds_all_pairs():
    r = np.random.default_rng(1)
    centre = r.integers(0, 2**63, 60, dtype=np.uint64)
    codes = np.unique(np.concatenate([centre, centre ^ (np.uint64(1) << r.integers(0, 64, 60).astype(np.uint64)), centre ^ np.uint64(0b1011), r.integers(0, 2**63, 500, dtype=np.uint64)]))
    group = r.integers(0, 3, len(codes))
    index = S.GrayIndex(codes, group)
    found = {tuple(sorted((int(index.codes[i]), int(index.codes[j])))) for a, b in index.near(3) for i, j in zip(a, b)}
    want = {tuple(sorted((int(x), int(y)))) for i, x in enumerate(codes) for j, y in enumerate(codes[:i]) if group[i] == group[j] and (int(x) ^ int(y)).bit_count() <= 3}
    assert found == want and want


def test_gray_rank_is_the_inverse_of_the_code():
    n = np.arange(1000, dtype=np.uint64)
    assert (S.gray_rank(n ^ (n >> np.uint64(1))) == n).all()


def test_keep_one_and_empty(docs, by_id):
    df = docs([(4, "a b c d"), (2, "a b c d"), (9, "p q r s t"), (None, "z"), (5, None), (3, "")])
    assert by_id(S.keep_one(df), "doc_id") == [(None,), (2,), (3,), (9,)]
    assert S.keep_one(df).columns == df.columns
    assert S.near_duplicates(docs([])).count() == 0 and S.keep_one(docs([])).count() == 0


def test_chain_components(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)] + [(100, 101), (5, 5)], "u long, v long")
    got = {r.node: r.root for r in S.components(edges).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}
