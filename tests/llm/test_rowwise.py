"""Operators that judge each row: fertility, decontamination, counts, URLs."""

import hashlib
import math
import random
import re
from collections import Counter

import pytest

from gradsift.llm import entry, fertility, prefixcount, urlvocab, wumanber
from gradsift.llm.textkit import ALNUM_WORDS, BLANK_WORDS, words_in_parts, words_of

LONG = " ".join(f"w{i % 700}" for i in range(20_000))
TEXTS = ["", None, " \n\t ", "one", "Ünï  çödé\nÜnï", "a b c a b c a b c\n\na b c", LONG, "#x|y*\n#x|y*\n<b>", "\x00\x1f\x85nbsp\xa0x", "same row", "same row", "日本語 テスト кириллица " * 30]
BLANK = r"[^\x20\x09-\x0D]+"
ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def lower(s):
    return re.sub("[A-Z]", lambda m: m[0].lower(), s)


def table(spark, texts=TEXTS):
    rows = [(i, t, "en" if i % 2 else None, "x") for i, t in enumerate(texts)]
    # columns that clash with those that operators add
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, kept string").withColumnRenamed("kept", "n_words")


def base_by_hand(t):
    ws = re.findall(BLANK, t or "")
    three = Counter(tuple(ws[i : i + 3]) for i in range(len(ws) - 2))
    hit = {i + j for i in range(len(ws) - 2) if three[tuple(ws[i : i + 3])] > 1 for j in range(3)}
    seen, dup = set(), 0
    for line in (t or "").split("\n"):
        if re.search(BLANK, line):
            dup += line in seen
            seen.add(line)
    failed = len(ws) < 50 or 100 * len(hit) > 50 * len(ws)
    return len(ws), sum(map(len, ws)), len(re.findall(r"[#*$%&|<>]", t or "")), dup, len(hit), failed


def test_fertility_base_counts_match_brute_force(spark):
    got = {r.doc_id: r for r in fertility.score(table(spark), keep=["doc_id"]).collect()}
    for i, t in enumerate(TEXTS):
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == base_by_hand(t), repr(t)[:40]
        assert not (r.base_failed and r.kept)


def test_fertility_measures_match_the_library(spark):
    import math

    import public_tokenizers
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(fertility.VOCABULARY))
    got = {r.doc_id: r for r in fertility.score(table(spark), keep=["doc_id"]).collect()}
    for i, t in enumerate(TEXTS):
        ids = [x for w in re.findall(BLANK, t or "") for x in model.encode(w)]
        n, r = len(ids), got[i]
        assert r.n_tokens == n
        assert r.byte_share == pytest.approx(sum(map(model.is_byte, ids)) / max(n, 1))
        assert r.token_entropy == pytest.approx(-sum(c / n * math.log2(c / n) for c in Counter(ids).values()) if n else 0.0, abs=1e-6)


def test_fertility_rejects_outside_the_band_and_keeps_inside(spark):
    rng = random.Random(1)
    prose = " ".join(rng.choice("the house of my father stands near an old river where children play and people walk".split()) + rng.choice(["", "s", "ed"]) + str(i % 9) for i in range(120))
    rows = table(spark, ["", prose, "qzxvkj" * 400 + " " + " ".join("zq%dxk%d" % (i, i) for i in range(90))])
    tight = {"en": fertility.Band(50, 60, 0, 0)}
    # the band that this made-up prose, a digit on every word, lies within
    wide = {"en": fertility.Band(1.7, 6.5, 0.05, 0.57)}
    kept = {r.doc_id: r.kept for r in fertility.score(rows, languages=wide, keep=["doc_id"]).collect()}
    assert kept[1] and not kept[0]
    spread = {r.doc_id: r.token_entropy for r in fertility.score(rows, keep=["doc_id"]).collect()}
    edge = {"en": fertility.Band(2.3, 2.4, 0.05, spread[1] / math.log2(306) - 1e-6)}
    assert fertility.score(rows, languages=edge, keep=["doc_id"]).where("kept").select("doc_id").collect()[0][0] == 1
    assert not any(r.kept for r in fertility.score(rows, languages=tight, scripts={"other": tight["en"], "latin": tight["en"]}, keep=["doc_id"]).collect())


def test_passing_keeps_rows_unchanged(spark):
    rows = table(spark)
    kept = {r.doc_id for r in fertility.score(rows, keep=["doc_id"]).where("kept").collect()}
    got = fertility.passing(rows)
    assert got.columns == rows.columns and {r.doc_id for r in got.collect()} == kept


def test_scripts():
    import numpy as np

    texts = ["plain", "日本語 x", "привет", "123", "é", ""]
    raw = [t.encode() for t in texts]
    offsets = np.cumsum([0, *map(len, raw)])
    assert fertility.scripts_of(np.frombuffer(b"".join(raw), np.uint8), offsets) == ["latin", "cjk", "cyrillic", "other", "latin", "other"]


def windows_by_hand(items, size=10):
    out = {}
    for item, t in items:
        w = re.findall(ALNUM, lower(t or ""))
        for i in range(max(1, len(w) - size + 1)) if w else ():
            out.setdefault(tuple(w[i : i + size]), set()).add(item)
    return out


def hits_by_hand(t, windows):
    w = re.findall(ALNUM, lower(t or ""))
    hit, items = set(), set()
    for p, who in windows.items():
        for i in range(len(w) - len(p) + 1):
            if tuple(w[i : i + len(p)]) == p:
                hit |= set(range(i, i + len(p)))
                items |= {x for x in who if x is not None}
    return len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit)


@pytest.mark.parametrize("share", [wumanber.SHARE_BYTES, 400])
def test_wu_manber_matches_brute_force(spark, monkeypatch, share):
    monkeypatch.setattr(wumanber, "SHARE_BYTES", share)
    rng = random.Random(5)
    vocab = ["the", "of", "and", "to", "Alpha", "beta", "gämma", "x1", "zz"]
    line = lambda n: " ".join(rng.choice(vocab) for _ in range(n))
    items = [(str(i), line(rng.randint(1, 16))) for i in range(25)] + [("9", None), (None, line(12)), ("7", ""), ("8", "...")]
    texts = [line(rng.randint(0, 80)) for _ in range(60)] + [items[3][1].upper() + "! " + items[4][1], None, "", LONG]
    bench = spark.createDataFrame(items, "item_id string, text string")
    windows = windows_by_hand(items)
    got = {r.doc_id: r for r in wumanber.search(table(spark, texts), bench, keep=["doc_id"]).collect()}
    for i, t in enumerate(texts):
        r = got[i]
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) == hits_by_hand(t, windows), i
    clean = {r.doc_id for r in wumanber.clean(table(spark, texts), bench).collect()}
    assert clean == {i for i, t in enumerate(texts) if not hits_by_hand(t, windows)[4]}


def cut_words(texts):
    import numpy as np

    raw = [t.encode() for t in texts]
    return words_of(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]), ALNUM_WORDS, lower=True)


def test_wu_manber_skips(monkeypatch):
    """Shifts pass over words that no window can end in."""
    w = cut_words([" ".join(f"p{i}" for i in range(10))])
    s = wumanber.Searcher(w, w.first, 10)
    assert s.most == 9 and sorted(s.steps) == list(range(9)) and len(s.ends) == 1
    read = []
    plain = wumanber.Searcher.shifts
    monkeypatch.setattr(wumanber.Searcher, "shifts", lambda self, keys: read.append(len(keys)) or plain(self, keys))
    start, test = s.occurrences(cut_words([LONG, "a b " + " ".join(f"P{i}" for i in range(10)) + " p0 p1"]))
    assert start.tolist() == [20_002] and test.tolist() == [0] and sum(read) < 20_000 / 8


def test_a_large_benchmark_is_made_into_tables_in_seconds():
    import time

    import pyarrow as pa

    rng = random.Random(7)
    words = [f"w{rng.randrange(50_000)}" for _ in range(700_000)]
    items = [" ".join(words[i : i + 70]) for i in range(0, len(words), 70)]
    began = time.perf_counter()
    tables = wumanber.Tables(pa.table({"item": [str(i) for i in range(len(items))], "text": items}), 10)
    assert time.perf_counter() - began < 20 and len(tables.searchers[0].first) == len(items) * 61
    text, word, of, item = tables.search(cut_words(["nothing here", "x " + items[5], LONG]))
    assert set(text.tolist()) == {1} and word.tolist() == list(range(1, 71)) and (of.tolist(), item.tolist()) == ([1], [5])


def test_clashing_columns_stay(spark):
    rows = spark.createDataFrame([(1, "a b", "x", 5, "y", 3)], "doc_id long, text string, hit_words string, n_hit int, hit_items string, _hit int")
    bench = spark.createDataFrame([("q", "b")], "item_id string, text string")
    got = wumanber.search(rows, bench).first()
    assert (got.hit_words, got.n_hit, got.hit_items, got._hit, got.contaminated) == ("x", 1, "y", 3, True)
    assert tuple(fertility.score(table(spark)).where("doc_id = 3").select("n_words").first()) == (1,)


def test_empty_tables(spark):
    docs = table(spark, [])
    bench = spark.createDataFrame([], "item_id long, text string")
    assert wumanber.search(docs, bench, keep=["doc_id"]).count() == 0
    assert wumanber.search(table(spark), bench, keep=["doc_id"]).where("contaminated").count() == 0
    assert fertility.score(docs).count() == 0 and prefixcount.token_counts(docs).count() == 0


def test_prefix_counts_match_the_library():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    mine, theirs = prefixcount.PrefixCounter(path), Tokenizer.from_file(path)
    count = lambda s: len(theirs.encode(s, add_special_tokens=False).ids)
    rng = random.Random(3)
    parts = [*"aeist 'relvmd  \n\t!?0129éß", "<|endoftext|>", "'re", "'ll", "中", "   ", "\u2003", "\x85", "\x1c", "🙂", "the ", "ing "]
    for _ in range(400):
        s = "".join(rng.choice(parts) for _ in range(rng.randint(0, 14)))
        want = [count(s[:i]) for i in range(len(s) + 1)]
        assert mine.prefixes(s) == want, repr(s)
        assert mine.total(s) == want[-1]
        for limit in (1, 3, 6):
            assert mine.longest_within(s, limit) == max(i for i, c in enumerate(want) if c <= limit)


def test_pieces_match_the_library_on_all_code_points():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    mine, cutter = prefixcount.PrefixCounter(path), Tokenizer.from_file(path).pre_tokenizer
    for c in range(prefixcount.NARROW):
        s = f"a{chr(c)}1{chr(c)}{chr(c)} b"
        assert mine.pieces(s) == [s[a:b] for _, (a, b) in cutter.pre_tokenize_str(s)], hex(c)


def test_token_counts_table(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    theirs = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    for r in prefixcount.token_counts(table(spark), keep=["doc_id"]).collect():
        t = TEXTS[r.doc_id] or ""
        n = len(theirs.encode(t, add_special_tokens=False).ids)
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(t.encode()), n, n > 512)
    rows = prefixcount.prefix_table(table(spark, ["ab cd", None]), keep=["doc_id"]).collect()
    assert [len(r.prefix_tokens) for r in sorted(rows)] == [6, 1]


URLS = [
    (None, "", "", None, "allow"),
    ("no scheme /en/", "", "", None, "allow"),
    ("http://A.Example.COM/en/7?x", "a.example.com", "/en/7", "example.com/en/7", "allow"),
    ("http://x.com/en/9", "x.com", "/en/9", "com/en/", "block"),
    ("http://notcom/en/9", "notcom", "/en/9", None, "allow"),
    ("https://example.net/de/81#y", "example.net", "/de/81", "example.net/de/8", "block"),
    ("https://other.net/de/casino", "other.net", "/de/casino", "net/de/", "allow"),
    ("ftp://free-bets.example.org/es", "free-bets.example.org", "/es", None, "block"),
    ("http://free.example.org/freebets", "free.example.org", "/freebets", None, "allow"),
    ("http://essex.example.org/", "essex.example.org", "/", None, "allow"),
    ("http://sex.example.org", "sex.example.org", "", None, "block"),
    ("http://a?b#c://d/e", "a", "", None, "allow"),
    ("http://ésex.org/Free/FREE", "ésex.org", "/Free/FREE", None, "allow"),
]


def test_urls(spark):
    pages = spark.createDataFrame([(i, u[0]) for i, u in enumerate(URLS)], "page_id long, url string")
    got = {r.page_id: r for r in urlvocab.judge(pages, keep=["page_id"]).collect()}
    for i, (_, host, path, rule, verdict) in enumerate(URLS):
        r = got[i]
        assert (r.host, r.path, r.rule, r.verdict) == (host, path, rule, verdict), URLS[i]
    assert got[12].soft_hits == 2 and got[12].soft_distinct == 1
    assert urlvocab.judge(pages.where("false")).count() == 0


def test_terms_of_all_languages_between_boundaries(spark):
    """One strict term or two unlike soft ones of any language block."""
    urls = {"http://a.test/casinos": "block", "http://a.test/casinosx": "allow", "http://a.test/gratis/kredit": "block", "http://a.test/apuestas-dinero": "block", "http://a.test/gratuit/gratuit": "allow", "http://gagner.rencontres.test/": "block", "http://a.test/" + "free/" * 30_000: "allow"}
    pages = spark.createDataFrame([(i, u, "v", 1) for i, u in enumerate([*urls, *urls])], "page_id long, url string, verdict string, host int")
    got = urlvocab.judge(pages).collect()
    assert len(got) == 2 * len(urls) and all(r.verdict == urls[r.url] for r in got)
    assert not set(urlvocab.STRICT) & set(urlvocab.SOFT)


def test_counting_replaces_clashing_columns(spark):
    rows = spark.createDataFrame([(1, "a b", 99, "x")] * 2, "doc_id long, text string, n_tokens int, over_limit string")
    got = prefixcount.token_counts(rows).collect()
    assert len(got) == 2 and got[0] == got[1] and (got[0].n_bytes, got[0].over_limit) == (3, False)


def test_words_in_parts_is_words_of():
    import numpy as np

    raw = [(t or "").encode() for t in TEXTS]
    data, offsets = np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)])
    a, b = words_of(data, offsets, BLANK_WORDS), words_in_parts(data, offsets, BLANK_WORDS, limit=64)
    for name in ("starts", "ends", "doc", "counts", "first", "hashes"):
        assert (getattr(a, name) == getattr(b, name)).all(), name
    found = [raw_text[s - o : e - o].decode() for raw_text, o in [(b"".join(raw), 0)] for s, e in zip(a.starts, a.ends, strict=True)]
    assert found == [w for t in TEXTS for w in re.findall(BLANK, t or "")]


def test_queries_run_on_whole_tables(spark, sf):
    n = spark.read.parquet(f"{sf}/documents.parquet").count()
    for name in ("op1_token_fertility", "op2_wu_manber", "op4_prefix_token_counts"):
        assert entry.QUERIES[name](spark, sf).count() == n


def test_bands_part_labelled_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet").where("toxic = 0")
    got = fertility.score(docs.join(labels, "doc_id"), keep=["quality"]).where("not base_failed").groupBy("quality").agg({"*": "count", "n_tokens": "count"})
    n = {r["quality"]: r["count(1)"] for r in got.collect()}
    kept = {r["quality"]: r["count"] for r in fertility.score(docs.join(labels, "doc_id"), keep=["quality"]).where("kept").groupBy("quality").count().collect()}
    assert kept[1] >= 0.985 * n[1] and kept[0] <= 0.25 * n[0]
