"""BPE, HTML, toxicity, quality, substring and scoring operators against the library, brute force and held-out labels, with edge rows."""

import collections
import hashlib
import math
import random
import re
import struct
import time

import pytest
from pyspark.sql import functions as F

from tierdraw.llm import bpe, htmltext, lmscore, quality, substring, toxicity
from tierdraw.llm.queries import queries, tokenizer_path

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
EDGE = [(1, None), (2, ""), (3, " \n\t "), (4, "one two"), (5, "one two"), (5, "one two"), (None, "no id here"), (7, "x" * 30_000), (8, "The end. " * 4000), (9, "<|endoftext|> ΑΣ ab\x1ccd 日本 é")]


@pytest.fixture(scope="module")
def edge(spark):
    """Nulls, empty and very long texts, ties, repeated rows, and columns whose names clash with results."""
    rows = [(i, t, "en" if k % 2 else None, None, 0, 1.0, True) for k, (i, t) in enumerate(EDGE)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_tokens int, tox_score double, kept boolean")


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer_path())


def test_bpe_equals_library(library):
    c, rng = bpe.codec(tokenizer_path()), random.Random(1)
    alphabet = "abcdefghijklmnopqrstuvwxyzABCÉÀßΣİ'’ 0129\t\n\x1c\x85 　!?.,;:-_#@日本語한글éàñ́̀😀‍"
    texts = ["".join(rng.choice(alphabet) if rng.random() < 0.97 else rng.choice(["<|endoftext|>", "'s", "'ll", "the", "ing", "ΑΣ "]) for _ in range(rng.randint(0, 40))) for _ in range(4000)]
    texts += ["a" * 5000, "hahaha" * 800, "th" * 2000 + "e", "!" * 3000, "".join(rng.choice("abcdeinthr") for _ in range(3000))]
    for t in texts:
        ids = library.encode(t, add_special_tokens=False).ids
        assert c.encode(t) == ids
        assert c.decode(ids).decode() == library.decode(ids, skip_special_tokens=False)


def test_bpe_rows(spark, edge, library):
    got = bpe.encode_column(edge, tokenizer_path(), "text", digests=True)
    assert got.columns.count("n_tokens") == 1
    for r in got.collect():
        ids = library.encode(r["text"] or "", add_special_tokens=False).ids
        assert r["n_tokens"] == len(ids) and r["ids_sha256"] == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    assert bpe.encode_column(edge.limit(0), tokenizer_path(), "text", digests=False).count() == 0


def test_html_templates():
    parts = "<h1>A title</h1><p>First paragraph, long enough &amp; with   marks.<p>Second <b>bold</b>ness, it is.</p><ul><li>One item<li>Two items</ul>"
    want = "A title First paragraph, long enough & with marks. Second boldness, it is. One item Two items"
    shells = [
        "<html><head><title>T</title><style>p{{}}</style><script>var t='</p>';</script></head><body><nav><a href=x>Menu</a></nav><!-- c --><div class='ad'>Buy now.</div><article>{}</article><footer>Foot, note.</footer></body></html>",
        "<body class='has-sidebar'><div class=cookie-notice>We use cookies, please agree.</div><header><h2>Site</h2></header><div id=content>{}<form><input><p>Join us.</p></form></div><div class='comments'><p>Nice post, I like it!</p></div><aside>More</aside>",
        "<main>{}<section id=comments><p>I disagree, sir.</p></section></main><div class='sidebar'>Side, bar.</div>",
    ]
    for s in shells:
        assert htmltext.main_text(s.format(parts)) == want
    assert htmltext.main_text(None) == htmltext.main_text("") == htmltext.main_text("<script>x</script>") == ""
    assert htmltext.main_text("plain words only") == "plain words only"
    assert htmltext.main_text("<p>" * 3000 + "deep. text") == "deep. text"


def test_html_linear_and_deep():
    """Broken markup ends in time in proportion to its length, and no depth is too deep."""
    began = time.time()
    for bad in ("<svg " * 200_000, '<a b="' * 150_000, "<a b='\"'" * 60_000, "<div><p>" + "<span>" * 5000 + "</p>" * 50_000, "<svg>" * 200_000, "<!--" * 200_000):
        htmltext.main_text(bad)
    assert time.time() - began < 10
    page = "<div>" * 5000 + "<article><p>The text, of an article.</p><aside>An advert, here.</aside></article>" + "</div>" * 5000
    assert htmltext.main_text(page) == "The text, of an article."
    assert htmltext.main_text("<article><p>Before, <svg width=1 /> after.</p></article>") == "Before, after."


def test_html_path_sums_and_ratios():
    """Scores from sums by path, worked out the long way; ratios part what names leave open."""
    prose = "A sentence, of some length. " * 8
    page = htmltext.read(f"<div class=x><p>{prose}<p>{prose}<ul><li><a href=1>one</a><li><a href=2>two</a><li><a href=3>more</a></ul></div>")
    scores = htmltext.path_scores(page)
    at = [n.path for n in page.nodes]
    own = {}
    for p in set(at):
        mine = [n for n in page.nodes if n.path == p and n.text.strip()]
        if mine:
            chars = [len("".join(n.text.split())) * (0.05**2 if n.link else 1) for n in mine]
            marks = [sum(c in htmltext.PUNCTUATION for c in n.text) for n in mine]
            own[p] = sum(chars) / len(mine) * (1 + sum(marks) / len(mine))
    seq = [n.path for n in page.nodes if n.text.strip()]
    for p in own:
        smooth = []
        for i in (i for i, x in enumerate(seq) if x == p):
            ws = [math.exp(-0.5 * ((i - j) / htmltext.SIGMA) ** 2) if abs(i - j) <= int(3 * htmltext.SIGMA) else 0 for j in range(len(seq))]
            smooth.append(sum(w * own[x] for w, x in zip(ws, seq, strict=True)) / sum(ws))
        assert scores[p] == pytest.approx((own[p] * sum(smooth) / len(smooth)) ** 0.25)
    links = "".join(f"<li><a href=/{k}>tag</a>" for k in range(40))
    mixed = f"<article><p>{prose * 20}</p><section class=related-work><p>{prose * 20}</p></section><div class=notice><p>{prose}</p></div></article><div>{links}</div>"
    assert htmltext.main_text(mixed) == " ".join([(prose * 20).strip()] * 2)
    plain = f"<div><p>{prose * 20}</p></div><div>{links}</div>"
    assert htmltext.main_text(plain) == (prose * 20).strip() != htmltext.main_text(plain, ratios=False)


def test_html_rows(spark):
    rows = spark.createDataFrame([(1, "u", None, "old"), (1, "u", None, "old"), (2, None, "<p>a&#xD800;b</p>", "old")], "page_id long, url string, html string, text string")
    got = htmltext.extract(rows).orderBy("page_id").collect()
    assert [r["n_chars"] for r in got] == [0, 0, 3] and htmltext.extract(rows.limit(0)).count() == 0


def test_substring_brute(spark, edge):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    sentence = lambda n: " ".join(word() for _ in range(n)) + ". "
    passage = "".join(sentence(rng.randint(3, 14)) for _ in range(8))
    rows = [(i, "".join(sentence(rng.randint(2, 15)) for _ in range(6)) + (passage if i % 3 == 0 else "") + sentence(9)) for i in range(30)]
    got = {r["doc_id"]: r for r in substring.drop_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, t in rows:
        want = t if i % 3 or i == 0 else t.replace(passage, "")
        assert got[i]["text"] == want
    out = substring.drop_repeats(edge).collect()
    assert len(out) == len(EDGE)
    by = collections.Counter(r["text"] for r in out)
    assert by["one two"] == 3 and by[None] == 1
    assert substring.drop_repeats(edge.limit(0)).count() == 0
    runs_of_8 = next(r for r in out if r["doc_id"] == 8)
    assert runs_of_8["n_removed"] >= 3900 and len(runs_of_8["text"]) < 400


def test_quality_brute(spark, edge):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang").unionByName(edge.filter("doc_id <> 5").select((F.col("doc_id") + 10**6).alias("doc_id"), "text", "lang"))
    for r in quality.measures(docs).join(docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).distinct(), "doc_id").collect():
        w = WORD.findall(r["text"])
        wins = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        seen, covered = collections.Counter(wins), set()
        for i, x in enumerate(wins):
            if seen[x] > 1:
                covered |= set(range(i, i + 5))
        lines = [x for x in r["text"].split("\n") if WORD.search(x)]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in r["text"]), len(lines) - len(set(lines)), len(covered))
    labels = spark.createDataFrame([], "doc_id long, quality int")
    assert quality.judge(edge.select("doc_id", "text", "lang"), labels).count() == len(EDGE)


def test_binomial_and_cutoffs(spark):
    from math import comb

    rows = spark.createDataFrame([(n, k) for n in (1, 30, 400) for k in range(0, min(n, 8))], "n long, k long")
    for r in rows.select("n", "k", quality.binomial_tail(F.col("n"), F.col("k"), 0.02).alias("p")).collect():
        want = sum(comb(r["n"], j) * 0.02**j * 0.98 ** (r["n"] - j) for j in range(r["k"] + 1))
        assert r["p"] == pytest.approx(want if r["k"] < r["n"] * 0.02 else 1.0)
    # good documents have few symbols, bad ones many: the cutoff lies between and rejects hardly any good one
    measured = spark.range(6000).select("id", F.lit("en").alias("stratum"), F.lit(100).cast("long").alias("n_words"), F.lit(1000).cast("long").alias("word_chars"), F.when(F.col("id") % 4 == 0, 200 + F.col("id") % 50).otherwise(F.col("id") % 7).cast("long").alias("n_symbols"), F.lit(0).cast("long").alias("n_dup_lines"), F.lit(0).cast("long").alias("n_repeat_words"), F.lit(5).cast("long").alias("n_lines"), F.lit(False).alias("base_failed")).withColumnRenamed("id", "doc_id")
    labels = spark.range(6000).select(F.col("id").alias("doc_id"), (F.col("id") % 4 != 0).cast("int").alias("quality"))
    cut = quality.cutoffs(measured, labels).first()
    assert 6 <= cut["cut_symbol"] < 200 and cut["cut_repeat"] is None
    few = labels.filter("doc_id < 200")
    assert quality.cutoffs(measured, few).count() == 0  # too few labels certify nothing


def test_toxicity_holdout_and_twins(spark, edge):
    rng = random.Random(5)
    names, bad, fill = ["muslim", "jewish", "christian", "hindu"], ["idiot", "scum"], [f"w{chr(97 + k)}x" for k in range(26)]
    rows = []
    for i in range(3000):
        toxic = rng.random() < 0.3
        # one group's name goes with toxic labels far more often
        name = [names[0]] if rng.random() < (0.6 if toxic else 0.1) else [rng.choice(names)]
        ws = rng.choices(fill, k=8) + name + ([rng.choice(bad)] if toxic else [])
        rng.shuffle(ws)
        rows.append((i, " ".join(ws), int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string, toxic int").cache()
    labels = docs.select("doc_id", "toxic")
    fair, plain = toxicity.train(docs.drop("toxic"), labels), toxicity.train(docs.drop("toxic"), labels, penalty=0.0)
    ask = lambda m, t: toxicity.score(spark.createDataFrame([(t,)], "text string"), m).first()["tox_score"]
    assert ask(plain, "muslim") > ask(fair, "muslim")  # a neutral mention
    gap = lambda m: abs(m[0].get("muslim", 0.0) - m[0].get("hindu", 0.0))
    assert gap(fair) < 0.5 * gap(plain)
    held = toxicity.score(docs, fair).filter(F.crc32(F.col("doc_id").cast("string")) % 5 == 0)
    assert held.agg(F.avg(((F.col("tox_score") >= 0.5).cast("int") == F.col("toxic")).cast("double"))).first()[0] > 0.97
    out = toxicity.score(edge, fair).collect()
    assert len(out) == len(EDGE) and all(0 <= r["tox_score"] <= 1 for r in out)
    none = toxicity.train(edge, labels.limit(0))
    assert toxicity.score(edge, none).filter("tox_score >= 0.5").count() == 0
    kept = toxicity.without_toxic(edge, none)
    assert kept.columns == edge.columns and kept.filter("tox_score = 1.0").count() == len(EDGE)


def test_toxicity_twins_and_gradient():
    groups = {"g": ["red", "blue"], "h": ["north", "south", "west"]}
    assert toxicity.twin("A Red hat, red shoes", 3, groups) == "a blue hat, blue shoes"
    made = toxicity.twin("no group here", 5, groups)
    extra = set(made.split()) - {"no", "group", "here"}
    assert len(extra) == 1 and extra < {"red", "blue", "north", "south", "west"}
    assert toxicity.twin(None, 1, groups).strip() in {"red", "blue", "north", "south", "west"} and toxicity.twin("x", 1, {}) is None
    # a strong penalty makes twins equal where the labels alone would part them
    xs, twins, ys = [[0], [1], [0, 2], [1, 2]] * 25, [[1], [0], [1, 2], [0, 2]] * 25, [0, 1, 0, 1] * 25
    free, held = (toxicity.fit(xs, twins, ys, 3, penalty=p)[0] for p in (0.0, 100.0))
    assert abs(free[0] - free[1]) > 5 and abs(held[0] - held[1]) < 0.1


def test_substring_rows(spark):
    """Repeated rows, versions of one id, rows without id, and columns whose names clash."""
    one, two = ("Some words make this first sentence, and more of them do. And a second one follows it with as many words. " for _ in range(2))
    rows = [(1, one), (1, one), (1, one + "Own end here."), (2, "Start of it. " + two), (None, one), (3, None), (4, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_removed", F.lit("mine")).withColumn("N_sentences", F.lit(7))
    out = substring.without_passages(docs)
    assert out.columns == docs.columns
    got = sorted(((r["doc_id"], r["text"]) for r in out.collect()), key=repr)
    assert got == sorted([(1, one), (1, one), (1, one + "Own end here."), (2, "Start of it. "), (None, one), (3, None), (4, "")], key=repr)
    assert {r["n_removed"] for r in out.collect()} == {"mine"}


def test_quality_null_stratum_is_apart(spark):
    rows = [(k, "word " * 5 + f"w{k} " * 3 + "a b c d e f", None if k % 2 else "") for k in range(10)]
    strata = {r["stratum"] for r in quality.measures(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert strata == {None, ""}


def test_lm_edges(spark, edge):
    targets = spark.createDataFrame([(4,), (4,), (None,), (99,)], "doc_id long")
    got = lmscore.score(edge.select("doc_id", "text"), targets).collect()
    assert len(got) == len(EDGE)
    for r in got:
        if r["n_tokens"] == 0:
            assert r["score"] == 0.0
    low = [r["score"] for r in got if r["doc_id"] == 5]
    assert low[0] == low[1] < min(r["score"] for r in got if r["doc_id"] in (7, None))
    assert lmscore.score(edge.select("doc_id", "text").limit(0), targets).count() == 0


@pytest.mark.parametrize("name", ["op2_url_filter", "op3_ngram_join", "op7_quality", "op8_substring", "op9_lm_score"])
def test_sql(spark, name):
    import duckdb

    from tierdraw.llm.queries import oracle_sql

    con = duckdb.connect()
    for t in ("documents", "labels", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.sql(oracle_sql()[name])
    cols = sorted(want.columns)
    got = queries()[name](spark, SF).select(*cols).collect()
    assert sorted(map(repr, map(tuple, got))) == sorted(map(repr, want.select(", ".join(cols)).fetchall()))
