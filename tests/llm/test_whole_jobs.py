"""Forms of input that operators once passed over."""

import tracemalloc

import pytest

from vistapoint.llm import html_blocks, urls

PAGE = "https://h.org/a/b/p.html?q#f"
LINKS = [
    ('<meta content="0; url=https://o.org/t" http-equiv="refresh">', ["https://o.org/t"]),
    ("<META CONTENT='5;URL=page2.html' HTTP-EQUIV=Refresh />", ["https://h.org/a/b/page2.html"]),
    ('<meta http-equiv="refresh" content="0; url=\'../x\'">', ["https://h.org/a/x"]),
    ('<link rel="canonical" href="./c/../d"><link href="/e" rel="canonical">', ["https://h.org/a/b/d", "https://h.org/e"]),
    ("<link rel=canonical href=//o.org/x><link rel=canonical href='?z=1&amp;y=2'>", ["https://o.org/x", "https://h.org/a/b/p.html?z=1&y=2"]),
    ('<meta http-equiv="refresh" content="0; url=../../../up"><meta content="1;url=two" http-equiv="refresh">', ["https://h.org/up", "https://h.org/a/b/two"]),
    ('<link title="a > b" rel="alternate canonical" data-href="/no" href="https://o.org/..">', ["https://o.org/"]),
    ('<link rel="stylesheet" href="/canonical.css"><meta name="refresh" content="0; url=/no"><meta http-equiv="refresh" content="30">', []),
]


def test_all_forms_of_declared_links(spark):
    pages = [(f"{PAGE}{i}", html) for i, (html, _) in enumerate(LINKS)] + [("https://h.org", "<link rel=canonical href=top>"), (None, LINKS[0][0]), (PAGE, None)]
    got = {}
    for r in urls.page_links(spark.createDataFrame(pages, "url string, html string")).collect():
        got.setdefault(r.src, []).append(r.dst)
    assert got == {f"{PAGE}{i}": to for i, (_, to) in enumerate(LINKS) if to} | {"https://h.org": ["https://h.org/top"]}


def test_a_redirect_by_any_form_takes_the_verdict(spark):
    pages = spark.createDataFrame([("https://a.org/d/p", '<meta content="0; url=../bad/x" http-equiv="refresh">'), ("https://a.org/bad/x", "")], "url string, html string")
    out = urls.judge(pages, urls.rule_table(spark, [("block", "a.org", "/bad")]), urls.page_links(pages))
    assert {r.url: r.verdict for r in out.collect()} == {"https://a.org/d/p": "block", "https://a.org/bad/x": "block"}


TEXT = "The ferry left the small harbour at dawn and nobody on the pier knew when it would come back to take the others across the bay."


@pytest.mark.parametrize(
    "opening, closing",
    [("<div class='overflow-hidden'>", "</div>"), ("<div class='md:hidden content'>", "</div>"), ("<div class='content has-sidebar'>", "</div>"), ("<div class='post no-comments'>", "</div>"), ("<form>", "</form>"), ("<div class=banner><article>", "</article></div>"), ("<div class=comments><main>", "</main></div>"), ("<div class=widget>", "</div>")],
)
def test_wrapped_main_text_is_kept(opening, closing):
    page = f"<nav><a href=/>Home</a></nav>{opening}<h1>The ferry</h1><p>{TEXT}</p><p>{TEXT}</p>{closing}<footer>Terms</footer>"
    assert html_blocks.main_text(page, html_blocks.trained_tree()) == f"The ferry\n{TEXT}\n{TEXT}"


@pytest.mark.parametrize("opening", ["<div hidden>", "<div aria-hidden='true'>", "<div style='display: none'>", "<div class='site-footer'>", "<div class=comments><article>", "<div class='cookie-notice'>", "<aside>", "<div hidden><main>"])
def test_furniture_stays_out(opening):
    tag = opening[1:].split(">")[0].split()[0]
    page = f"<article><p>{TEXT}</p><p>{TEXT}</p></article>{opening}<p>{TEXT}</p></{tag}>"
    assert html_blocks.main_text(page, html_blocks.trained_tree()) == f"{TEXT}\n{TEXT}"


def test_packing_is_the_same_however_few_rows_are_strings_at_once(spark, monkeypatch):
    from vistapoint.llm import packing

    docs = spark.createDataFrame([(i, "word " * (37 * i % 900) if i % 9 else None) for i in range(250)], "doc_id long, text string").coalesce(1)
    small = sorted(map(tuple, packing.pack(docs).collect()))
    monkeypatch.setattr(packing, "ROWS_AT_ONCE", 10_000)
    assert packing.ROWS_AT_ONCE != 100 and len({r[0] for r in small}) == 250 and sorted(map(tuple, packing.pack(docs).collect())) == small


def test_a_word_memory_stays_below_its_bound_in_bytes():
    from vistapoint.llm import tokens

    tracemalloc.start()
    try:
        encoder = tokens.WordEncoder(tokens.default_tokenizer())
        before = tracemalloc.get_traced_memory()[0]
        for i in range(0, 800_000, 100):
            encoder.encode(" ".join(f"w{j}" for j in range(i, i + 100)))
        assert tracemalloc.get_traced_memory()[0] - before < 90e6 and len(encoder.young) + len(encoder.old) > 100_000
    finally:
        tracemalloc.stop()


def test_letters_are_remembered_once_and_encoded_as_the_tokenizer_does():
    from array import array

    from vistapoint.llm import tokens

    encoder = tokens.WordEncoder(tokens.default_tokenizer(), 50)
    words = ["house", "House", "house,", "HOUSE!", "été", "Été.", "ªº", "straße", "don't", "x''s", "a1b2", "naïve7", "<|x", "a<|b", "İx", "ŉa", "\x7fa", "é\x00", "中文", "é", "'", "7", "é'", "Été's"]
    assert all(encoder.encode(w) == array("I", encoder.tokenizer.encode(w, add_special_tokens=False).ids).tobytes() for w in words * 3)
    fresh = tokens.WordEncoder(tokens.default_tokenizer())
    fresh.encode("House, été")
    assert "house" in fresh.young and "house" not in fresh.parts and "été" not in fresh.parts
    text = " ".join(f"{w}{i % 60}" if i % 3 else w for i, w in enumerate(words * 40))
    assert encoder.encode(text) == array("I", encoder.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()
