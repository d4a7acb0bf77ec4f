"""Nulls, empty and long texts, ties, repeated rows, empty tables, and extra columns, for every operator and pipeline stage."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from vistapoint.llm import chat, decontam, html_blocks, minhash, packing, quality, suffix, tokens, toxicity, urls

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "word and another word with some more of them here " * 3000


def rows():
    texts = [None, "", " \t\n", "one", "one two", LONG, "same text here", "same text here", "Same  TEXT here", None]
    return [(i if i != 9 else None, t, "en", "s", len(t or "")) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([*rows(), rows()[6]], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


CLASHES = ("tier", "n_bytes", "kept", "score", "h", "key", "m", "rep", "host", "verdict", "signature", "t1", "words", "votes", "quality", "component", "node", "item_id", "start", "n")


@pytest.fixture(scope="module")
def clashing(docs):
    return docs.withColumns({c: F.lit("x") for c in CLASHES})


def test_packing(docs, none, clashing):
    for df in (docs, clashing):
        pieces = packing.pack(df).collect()
        assert sorted(p.doc_tokens for p in pieces if p.start == 0)[:4] == [1, 1, 1, 1]
        assert sum(p.length for p in pieces) == sum(p.doc_tokens for p in pieces if p.start == 0)
        assert all(len(p.ids) == 4 * p.length for p in pieces)
    assert packing.pack(none).count() == 0
    with pytest.raises(ValueError):
        packing.pack(docs, tiers=(100, 2048))


def test_quality(docs, none, clashing):
    for df in (docs, clashing):
        got = quality.judge_quality(df).collect()
        assert len(got) == 11 and all(r.n_words == 0 and r.base_failed and not r.kept for r in got if r.doc_id in (0, 1, 2, None))
    assert quality.judge_quality(none).count() == 0


def test_suffix(docs, none, clashing):
    for df in (docs, clashing):
        got = {r.doc_id: r for r in suffix.remove_repeats(df).collect() if r.doc_id is not None}
        assert got[0].n_bytes == got[1].n_bytes == 0 and got[6].n_removed == 0
        assert got[5].n_removed > 100_000 and len(got[5].kept) == got[5].n_bytes - got[5].n_removed
    assert suffix.remove_repeats(none).count() == 0
    assert suffix.remove_repeats(clashing).columns[:5] == DOCS.replace(" long", "").replace(" string", "").split(", ")


def test_suffix_snaps_to_characters(spark):
    text = "é" * 150
    df = spark.createDataFrame([(1, "a" + text + "xyz"), (2, "b" + text + "uvw")], "doc_id long, text string")
    got = {r.doc_id: r for r in suffix.remove_repeats(df).collect()}
    assert got[1].kept_text == "axyz" and got[2].kept_text == "buvw" and got[1].n_spans == 1


def test_decontamination(spark, docs, none, clashing):
    bench = spark.createDataFrame([(1, "Same text here"), (2, None), (3, ""), (4, "one, TWO!")], "item_id long, text string")
    for df in (docs, clashing):
        got = {(r.doc_id, r.item_id) for r in decontam.leaks(df, bench).collect()}
        assert got == {(6, 1), (7, 1), (8, 1), (4, 4)}
        assert sorted(r.doc_id for r in decontam.decontaminate(df, bench).collect() if r.doc_id is not None) == [0, 1, 2, 3, 5]
    assert decontam.leaks(none, bench).count() == 0
    assert decontam.leaks(docs, bench.where("false")).count() == 0


def test_minhash(docs, none, clashing):
    for df in (docs, clashing):
        got = [(r.doc_id, r.component_id, r.kept) for r in minhash.near_duplicates(df).collect()]
        assert len(got) == 11 and {g for g in got if g[0] in (6, 7, 8)} == {(6, 6, True), (7, 6, False), (8, 6, False)}
        assert (None, None, True) in got and (1, 1, True) in got
        kept = minhash.keep_one(df)
        assert kept.columns == df.columns and sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == [0, 1, 2, 3, 4, 5, 6]
    assert minhash.near_duplicates(none).count() == 0


def test_toxicity(spark, docs, none, clashing):
    labels = spark.createDataFrame([(0, 0), (4, 1), (4, 0), (5, None), (None, 1), (77, 1)], "doc_id long, toxic int")
    model = toxicity.fit(docs, labels)
    for df in (docs, clashing):
        got = toxicity.score(df, model)
        assert all(0 <= r.score <= 1 for r in got.collect()) and got.count() == 11
    assert toxicity.score(none, model).count() == 0
    assert toxicity.score(docs, toxicity.fit(docs, labels.where("false"))).where("score = 0.5").count() == 11


def test_urls(spark):
    rules = urls.rule_table(spark, [("block", "net", "/"), ("allow", "a.net", "/en/"), ("block", "x.org", "/")])
    pages = spark.createDataFrame([(1, None), (2, ""), (3, "no scheme"), (4, "http://B.Net"), (5, "http://b.net/q?x=/en/"), (6, "https://www.a.net/en/p#t"), (7, "https://y.org/p"), (8, "https://y.org/p"), (9, "https://z.org/r"), (10, "https://x.org/s"), (11, "https://notnet/")], "page_id long, url string")
    links = spark.createDataFrame([("https://y.org/p", "https://x.org/gone"), ("https://z.org/r", "https://x.org/s"), ("https://z.org/r", "https://a.net/en/ok"), (None, "https://q.org/")], "src string, dst string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in urls.judge(pages.withColumns({"host": F.lit(1), "key": F.lit(2), "own": F.lit(3)}), rules, links).collect()}
    assert got[1] == got[2] == got[3] == ("", "", None, "allow")
    assert got[4] == ("b.net", "", None, "allow") and got[5] == ("b.net", "/q", "net/", "block") and got[6] == ("www.a.net", "/en/p", "a.net/en/", "allow")
    assert got[7][3] == got[8][3] == "block" and got[9][3] == "allow" and got[10][2:] == ("x.org/", "block") and got[11][2:] == (None, "allow")
    assert urls.judge(pages.where("false"), rules, links).count() == 0


def test_page_links(spark):
    html = '<head><link href="/c" rel="canonical"><meta http-equiv="Refresh" content="0; url=https://o.org/t"></head>'
    got = {(r.src, r.dst) for r in urls.page_links(spark.createDataFrame([("https://h.org/a?b", html), ("https://h.org/z", None), (None, html)], "url string, html string")).collect()}
    assert got == {("https://h.org/a?b", "https://h.org/c"), ("https://h.org/a?b", "https://o.org/t")}


def test_chat(spark):
    schema = f"conv_id long, turn long, role string, parts array<{chat.PART}>"
    text = lambda t: ("text", t, None, None, None, None, None)
    hostile = ["<|end|>", "\\<|", "<\\|", "\\\\", "<|<|text|>\\", None, "", "a\nb"]
    rows = [(1, 2, "assistant", [text("see"), ("image", None, "u1", 56, 29, None, None), ("audio", None, "u2", None, None, 2.5, None)]), (1, 1, "user", [text("hi"), ("document", None, "u3", None, None, None, 3)]), (2, None, None, None), (3, 0, "assistant", [])]
    rows += [(4, i, h, [text(h)]) for i, h in enumerate(hostile)] + [(5, 0, "user", [text("x")])] * 2
    out = chat.format_conversations(spark.createDataFrame(rows, schema))
    got = {r.conv_id: r for r in out.withColumns({"turns": chat.parsed_turns(F.col("formatted")), "loss": chat.loss_text(F.col("segments"))}).collect()}
    assert [t.role for t in got[1].turns] == ["user", "assistant"] and got[1].loss == "see<|image 1.1|><|audio 1.2|>" and got[1].expanded_tokens == 2 * 2 + 63 + 768
    assert [(a.kind, a.uri, a.tokens) for a in got[1].attachments] == [("document", "u3", 768), ("image", "u1", 4), ("audio", "u2", 63)]
    assert [t.text for t in got[4].turns] == [h or "" for h in hostile] == [t.role for t in got[4].turns]
    assert [(t.role, t.text) for t in got[2].turns] == [("", "")] and got[5].n_turns == 2
    assert chat.format_conversations(spark.createDataFrame([], schema)).count() == 0


def test_token_counts(docs, none, clashing):
    for df in (docs, clashing):
        total = tokens.context_totals(tokens.length_histogram(df, end_ids=1)).orderBy("n_tokens").collect()
        assert total[0].n_tokens == 1 and total[0].n_docs == 4 and total[-1].docs_over == 0 and total[-1].quantile == 1.0
    assert tokens.context_totals(tokens.length_histogram(none)).count() == 0


def test_html(spark):
    pages = [(1, "u", None), (2, "u", ""), (3, None, "<article><p>A &amp; b<br>c&nbsp;d<p>e</article><footer>f</footer>"), (4, "u", "<article><p>x</p><script>var a='</p>';</script><!-- <p>no</p> --><p>y <b>z</b></p>"), (5, "u", "<p"), (6, "u", "<article><h1>T</h1><p>p</p><div class='comments'><p>c</p></div><form>q</form></article>")]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("text", F.lit("clash"))
    assert {r.page_id: r.text for r in html_blocks.extract(df).collect()} == {1: "", 2: "", 3: "A & b\nc d\ne", 4: "x\ny z", 5: "", 6: "T\np"}
    assert html_blocks.extract(df.where("false")).count() == 0


def test_stages(spark, docs, none, tmp_path):
    spark.createDataFrame([(4, 1, 1), (6, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, "one two")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    for df in (docs, none):
        for name, stage in corpus_pipeline.STAGES:
            out = stage(spark, df, str(tmp_path))
            if name != "packing":
                assert out.columns == df.columns
            assert (out.count() == 0) == (df is none)
