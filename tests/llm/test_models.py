import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from tilemine.llm import language as G, pieces as P, quality as Q, tokens as T

TEXTS = [None, "", "a", "  a  b ", "▁x", "\n", " ", "x▁ ý", "<s> a </s> <unk>", "ﬁ Å Å", "日本 語", " \U0001f600", "don't STOP  now\t\tplease", "x" * 5000, "é" * 3000 + " y", "<|endoftext|>a<|startoftext|> b", "á ́b", "1234 5,6.7!!! ~~", "A" * 300 + " " + "b" * 300]


def test_pieces_are_those_of_the_library(docs, by_id):
    sp = P.load()
    got = by_id(P.digests(docs(list(enumerate(TEXTS)))), "doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
    for (i, n, ids_sha, text_sha), text in zip(got, TEXTS):
        ids = sp.encode(text or "")
        assert (n, ids_sha, text_sha) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(sp.decode(ids).encode() if ids else b"").hexdigest()), repr(text)


def test_one_table_for_the_corpus_gives_the_same_ids(docs):
    df = docs(list(enumerate(TEXTS)) + [(3, TEXTS[3]), (None, "a b a b a")])
    key = lambda r: (r.doc_id is not None, r.doc_id or 0, r.ids)
    assert sorted(P.encoded_by_join(df).collect(), key=key) == sorted(P.encoded(df).collect(), key=key)
    assert P.encoded_by_join(docs([])).count() == 0
    chunks = P.distinct_chunks(docs([(1, "a b a"), (2, "a")])).where("chunk IS NOT NULL")
    assert sorted((r.doc_id, r.chunk, r.places) for r in chunks.collect()) == [(1, " a", [0, 2]), (1, " b", [1]), (2, " a", [0])]


def test_round_trip_tables(docs, spark):
    df = docs([(1, "a bc"), (2, None)])
    ids = P.encoded(df)
    assert {r.doc_id: r.text for r in P.decoded(ids).collect()} == {1: "a bc", 2: ""}
    assert P.digests(docs([])).count() == 0


def test_chunk_table_may_be_emptied():
    sp, r = P.load(), random.Random(1)
    small = P.Chunks(sp, table_chars=300, long_chunk=8)
    for _ in range(60):
        text = "".join(r.choice("ab é▁\n ß") for _ in range(r.randrange(80)))
        assert [i for ids, _ in small.blocks(text, 7) for i in ids] == sp.encode(text), repr(text)


def test_token_counts(docs, by_id):
    t = Tokenizer.from_file(public_tokenizers.path(T.FILE))
    got = by_id(T.counts(docs(list(enumerate(TEXTS))), limit=5), "doc_id", "n_bytes", "n_tokens", "over_limit")
    want = [len(t.encode(x or "", add_special_tokens=False).ids) for x in TEXTS]
    assert got == [(i, len((x or "").encode()), n, n > 5) for (i, x), n in zip(enumerate(TEXTS), want)]
    assert T.counts(docs([])).count() == 0


@pytest.mark.parametrize("chunk,overlap", [(40, 5), (100, 30), (64, 1)])
def test_resynchronised_counts(chunk, overlap):
    t, r = Tokenizer.from_file(public_tokenizers.path(T.FILE)), random.Random(7)
    counter = T.Counter(T.load(), chunk, overlap, T.load_plain())
    alphabet = ["word", "Don't", " ", "  ", "\n", "!!", "é", "é", "́", "日本", "7", "<|endoftext|>", "<|", "|>", "x" * 90, " ", "'s", "\U0001f600"]
    for _ in range(150):
        text = "".join(r.choice(alphabet) + r.choice(["", " ", " "]) for _ in range(r.randrange(1, 120)))
        assert counter.count_long(text) == len(t.encode(text, add_special_tokens=False).ids), repr(text)
    assert counter.widened


def test_texts_that_skip_the_normaliser():
    """Every character below the combining marks, in small and capital form, in words and alone, has the library's tokens."""
    whole, counter = Tokenizer.from_file(public_tokenizers.path(T.FILE)), T.Counter(T.load(), plain=T.load_plain())
    signs = [chr(c) for c in range(0x300)]
    texts = [f"{a}x{a} {a}" for a in signs] + ["".join(signs[i : i + 40]) for i in range(0x2D8)] + ["A\u0301 B", "\u0130stanbul", "<|ENDOFTEXT|> <|endoftext|>", "\u212b\u03a3"]
    assert counter.count_all(texts) == [len(t) for t in whole.encode_batch(texts, add_special_tokens=False)]


def test_long_texts_are_spliced_and_equal_the_library(spark, sf):
    """At the production sizes: most long texts of the table are counted by chunks, and every count is the library's."""
    texts = [r.text or "" for r in spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet").select("text").collect()]
    long = [t for t in texts if len(t) > T.CHUNK]
    counter, whole = T.Counter(T.load(), plain=T.load_plain()), Tokenizer.from_file(public_tokenizers.path(T.FILE))
    assert counter.count_all(long) == [len(t) for t in whole.encode_batch(long, add_special_tokens=False)]
    assert len(long) > 3 and counter.spliced >= sum(-(-len(t) // (2 * T.CHUNK)) for t in long)
    huge = "\n".join(long)
    assert counter.count_long(huge) == len(whole.encode(huge, add_special_tokens=False))
    solid = "x" * 20_000
    assert counter.count_long(solid) == len(whole.encode(solid, add_special_tokens=False))


def brute_quality(text):
    ws = (text or "").encode().split()
    covered = set()
    grams = [tuple(ws[i : i + 5]) for i in range(len(ws) - 4)]
    for i, g in enumerate(grams):
        if grams.count(g) > 1:
            covered.update(range(i, i + 5))
    lines = [x for x in (text or "").split("\n") if x.encode().split()]
    return len(ws), sum(len(w.decode()) for w in ws), sum(c in "#*$%&|<>" for c in text or ""), len(lines) - len(set(lines)), len(covered)


def quality_texts():
    r = random.Random(9)
    return [" ".join(r.choices(["a", "bé", "c#", "*"], k=r.choice([0, 4, 5, 9, 40]))) + r.choice(["", "\nx\nx\n \n", "\n"]) for _ in range(60)] + [None, "", "\x0b\x0c", "w " * 30, "\xa0 a"]


def test_quality_figures(docs, by_id):
    texts = quality_texts()
    got = by_id(Q.assess(docs(list(enumerate(texts)))), "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    assert got == [(i, *(x := brute_quality(t)), x[0] < 10 or 100 * x[4] > 20 * x[0]) for i, t in enumerate(texts)]


def test_verdict_does_not_depend_on_the_order(docs, by_id):
    df = docs(list(enumerate(quality_texts())))
    back = dict(reversed(Q.RULES.items()))
    assert by_id(Q.assess(df), "doc_id", "kept") == by_id(Q.assess(df, back, 3), "doc_id", "kept")
    kept = {r.doc_id for r in Q.assess(df).collect() if r.kept}
    assert {r.doc_id for r in Q.keep_good(df).collect()} == kept and Q.keep_good(df).columns == df.columns
    assert {r.doc_id for r in Q.keep_good(df, dict(reversed((Q.BASE | Q.RULES).items())), 1).collect()} == kept
    assert Q.assess(docs([])).count() == 0 and Q.keep_good(docs([])).count() == 0


def test_cascade_puts_the_cheap_rejecting_rule_first():
    import time

    rules = {"slow": lambda x: time.sleep(0.001) or True, "never": lambda x: False, "fast": lambda x: True}
    measured = Q.measure([b"one two three four five six seven eight nine ten"] * 20, rules)
    assert Q.rank(measured)[0] == "fast" and measured["never"][1] == 0 and measured["slow"][1] == 20


def test_a_rejected_text_never_meets_the_dear_figures():
    x = Q.Text(b"### *** $$$ " * 50)
    turn = ["symbols", "repeated_windows", "few_words"]
    assert Q.first_against(x, turn, Q.BASE | Q.RULES) == "symbols"
    assert "n_symbols" in x.__dict__ and "n_repeat_words" not in x.__dict__ and "lines" not in x.__dict__


def test_rules_on_lines_and_wording(docs):
    clean = " ".join(f"word{i}" for i in range(60))
    texts = {1: clean, 2: "\n".join(f"- item{i} has word{i} and{i} more{i}" for i in range(9)), 3: "\n".join(f"some{i} words{i} here{i} go{i} on{i}..." for i in range(4)), 4: clean + " Lorem IPSUM dolor",
             5: clean + " you IDIOT, you moron!", 6: clean + " an idiot", 7: " ".join(f"w{i}" for i in range(500)) + " idiot moron", 8: "• " + clean + "\n" + clean + " end", 9: clean.replace("word7 ", "ıdıot mörön ")}
    assert {r.doc_id: r.rule for r in Q.assess(docs(list(texts.items()))).collect()} == {1: None, 2: "bullets", 3: "ellipses", 4: "placeholder", 5: "insults", 6: None, 7: None, 8: "base" if Q.base_failed(Q.Text(texts[8].encode())) else None, 9: None}


def test_words_of_long_texts_come_in_stretches():
    from tilemine.llm.common import word_lists

    r = random.Random(5)
    for size in (1, 3, 10, 1000):
        for _ in range(40):
            body = "".join(r.choice(["a", "bc", " ", "\n", "\t ", "é", "\xa0"]) for _ in range(r.randrange(60))).encode()
            assert [w for ws in word_lists(body, size) for w in ws] == body.split()


def test_very_long_text_has_a_verdict(docs):
    text = " ".join(f"word{i}" for i in range(300_000))
    assert [(r.n_words, r.kept) for r in Q.assess(docs([(1, text)])).collect()] == [(300_000, True)]


def test_language(spark, sf):
    docs = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    rows = G.identify(docs, G.learn(docs)).join(docs.select("doc_id", "lang", "text"), "doc_id").collect()
    held = [r for r in rows if zlib.crc32(str(r.doc_id).encode()) % 3 == 1]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    letters = [r for r in held if any(c.isalpha() for c in r.text)]
    assert np.mean([r.lang == r.lang_pred for r in letters]) > 0.98
    assert all(0 <= r.score <= 1 for r in rows)
    trusted = [r for r in letters if not r.rejected]
    assert len(trusted) >= 0.9 * len(letters) and np.mean([r.lang == r.lang_pred for r in trusted]) >= np.mean([r.lang == r.lang_pred for r in letters])


def test_rejection_keeps_known_languages_and_refuses_others(docs, spark, sf):
    """Held-out pieces in learned languages pass at the fitted limit; strings of letters in none of them mostly do not, and what passes is right."""
    source = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    model = G.learn(source)
    held = [r for r in source.where("lang IS NOT NULL AND text IS NOT NULL").collect() if zlib.crc32(str(r.doc_id).encode()) % 3 == 1]
    pieces = [(r.lang, " ".join(r.text.split()[:25])) for r in held]
    odd = ["xq zwk qqj vvx kzz wjq" * 3, "тест на другом языке совсем", "これは 日本語 の 文章 です", "zxcv qwrt plkj hgfd"] * 5
    got = {r.doc_id: r for r in G.identify(docs([(i, t) for i, t in enumerate([t for _, t in pieces] + odd)]), model).collect()}
    passed = [i for i in range(len(pieces)) if not got[i].rejected]
    assert len(passed) >= 0.85 * len(pieces) and np.mean([got[i].lang_pred == pieces[i][0] for i in passed]) > 0.97
    assert np.mean([got[len(pieces) + i].rejected for i in range(len(odd))]) >= 0.75


def test_sample_is_bounded_by_bytes_and_equal_rows_are_one(spark):
    df = spark.createDataFrame([(None, "der die das " * 50, "de")] * 300 + [(i, f"the of and {i} " * 50, "en") for i in range(300)], "doc_id long, text string, lang string")
    assert G.learn(df, sample_rows=200).languages == ["de", "en"] or G.learn(df, sample_rows=200).languages == ["en"]
    assert len(G.learn(df, sample_bytes=1).languages) <= 2


def test_language_edges(docs):
    model = G.train([("der die das und " * 20, "de"), ("the of and to " * 20, "en")] * 30)
    got = {r.doc_id: r.lang_pred for r in G.identify(docs([(1, None), (2, ""), (3, "123 !!"), (4, "the and of"), (5, "und die das")]), model).collect()}
    assert got == {1: "und", 2: "und", 3: "und", 4: "en", 5: "de"}
    assert [r.lang_pred for r in G.identify(docs([(1, "the")]), G.train([])).collect()] == ["und"]
    assert G.identify(docs([]), model).count() == 0
    rejected = G.Predictor(model)("zzzz qqqq", 0.999999)
    assert rejected[0] == "und"


def test_word_table_may_be_emptied():
    model = G.train([("aa bb cc " * 9, "x"), ("dd ee ff " * 9, "y")] * 10)
    wide, small = G.Predictor(model), G.Predictor(model, 60_000)
    texts = [" ".join(f"{a}{b}" for a in "abcdef" for b in "ghij"), " ".join("abcdefghij"[i % 10] * (i % 5 + 1) for i in range(120_000))]
    for t in texts * 2:
        assert small(t)[0] == wide(t)[0] and abs(small(t)[1] - wide(t)[1]) < 1e-6
