"""The registered queries against plain Python on the smallest tables, and their SQL where there is some."""

import collections
import hashlib
import re
import zlib

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from vistapoint.llm import components, minhash, queries, suffix, tokens

DIR = "/root/testdata/sf0.001"
WORD = re.compile("[^\x20\x09-\x0d]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@pytest.fixture(scope="module")
def texts():
    return {i: t or "" for i, t in duckdb.sql(f"select doc_id, text from '{DIR}/documents.parquet'").fetchall()}


def run(spark, name):
    return queries.queries()[name](spark, DIR)


def test_packing_round_trip(spark, texts):
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(tokens.default_tokenizer())
    rows = run(spark, "op1_packing").collect()
    by_doc, by_window = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        by_doc[r.doc_id].append(r), by_window[r.sequence_id].append(r)
    for i, t in texts.items():
        ids = np.array([*whole.encode(t, add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for r in sorted(by_doc[i], key=lambda r: r.start):
            assert (r.start, r.doc_tokens, r.ids_crc32) == (at, len(ids), zlib.crc32(ids[at : at + r.length].tobytes()))
            at += r.length
        assert at == len(ids)
    for window in by_window.values():
        at = 0
        for r in sorted(window, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= 2048 and not at & (at - 1)
    groups = collections.defaultdict(set)
    for r in rows:
        groups[r.step_group].add(r.tier)
    assert all(len(g) == 1 for g in groups.values())


def test_quality_measures(spark, texts):
    for r in run(spark, "op2_quality_rules").collect():
        t = texts[r.doc_id]
        w = WORD.findall(t)
        lines = [x for x in t.split("\n") if WORD.search(x)]
        grams = collections.Counter(zip(w, w[1:], w[2:], strict=False))
        held = {j for k in range(len(w) - 2) if grams[(w[k], w[k + 1], w[k + 2])] > 1 for j in (k, k + 1, k + 2)}
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(held))
        assert r.base_failed == (len(w) < 50 or 100 * len(held) > 50 * len(w)) and not (r.kept and r.base_failed)


def brute_repeats(texts, length=200):
    raw = {i: t.encode() for i, t in texts.items()}
    seen = collections.Counter(b[s : s + length] for b in raw.values() for s in range(len(b) - length + 1))
    out = {}
    for i, b in raw.items():
        gone = bytearray(len(b))
        for s in range(len(b) - length + 1):
            if seen[b[s : s + length]] > 1:
                gone[s : s + length] = b"\1" * length
        out[i] = (len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(bytes(x for x, g in zip(b, gone, strict=True) if not g)).hexdigest())
    return out


def test_repeats(spark, texts):
    expected = brute_repeats(texts)
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in run(spark, "op3_suffix_array").collect()} == expected
    hot = suffix.remove_repeats(spark.read.parquet(f"{DIR}/documents.parquet"), hot=3, part_rows=4, block_bytes=5000)
    assert {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans) for r in hot.collect()} == {i: v[:3] for i, v in expected.items()}


def test_two_stage_order_is_the_suffix_array():
    rng = np.random.default_rng(3)
    for _ in range(20):
        body = rng.integers(97, 100, 400).astype(np.uint8).tobytes() + b"a" * 80 + rng.integers(97, 99, 50).astype(np.uint8).tobytes()
        text = np.frombuffer(body + bytes(80 + suffix.RUN + 8), np.uint8)
        n = len(body) + 1
        order = suffix.two_stage_order(text, np.array([0]), np.array([n]), 80)
        keys = [text[i : i + 80].tobytes() for i in order]
        assert sorted(order.tolist()) == list(range(n)) and keys == sorted(keys)
        common = suffix.adjacent_prefixes(text, order, 80)
        assert [next((j for j in range(80) if a[j] != b[j]), 80) for a, b in zip(keys, keys[1:], strict=False)] == common.tolist()


def test_leaks(spark, texts):
    plain = lambda t: " " + " ".join(re.findall(r"[^\W_]+", t.lower())) + " "
    items = [(i, plain(t)) for i, t in duckdb.sql(f"select item_id, text from '{DIR}/benchmark.parquet'").fetchall()]
    assert {(r.doc_id, r.item_id) for r in run(spark, "op4_decontamination").collect()} >= {(d, i) for d, t in texts.items() for i, b in items if b in plain(t)}


def brute_components(texts, size, percent=80):
    sets = {}
    for i, t in texts.items():
        w = WORD.findall(t.translate(LOW))
        sets[i] = set(zip(*[w[j:] for j in range(size)], strict=False)) if len(w) >= size else ({tuple(w)} if w else set())
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[:k]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in ids}


def test_near_duplicates(spark, texts):
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in run(spark, "op5_minhash").collect()} == brute_components(texts, 2)
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    small = minhash.near_duplicates(docs, minhash.Settings(), asking=(1,), chunk=3)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in small.collect()} == brute_components(texts, 5)


def test_pruning_rule_matches_the_posterior():
    s = minhash.Settings()
    rng = np.random.default_rng(0)
    for k, least in minhash.least_matches(s)[:2]:
        draws = rng.beta(least, k - least + 2, 400_000) if least else np.zeros(1)
        assert (draws >= 0.8).mean() < 1e-4 and 0 < least < 0.8 * k


def test_components_both_ways(spark):
    rng = np.random.default_rng(1)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 300, (220, 2))] + [(1000 + i, 1001 + i) for i in range(40)] + [(5, 5)]
    df = spark.createDataFrame(edges, "u long, v long")
    a = {tuple(r) for r in components.connected_components(df).collect()}
    assert a == {tuple(r) for r in components.connected_components(df, one_task_edges=10_000).collect()} and (1040, 1000) in a


def test_toxicity_held_out(spark):
    rows = queries.queries()["op7_toxicity"](spark, "/root/testdata/sf0.1").collect()
    labels = dict(duckdb.sql("select doc_id, toxic from '/root/testdata/sf0.1/labels.parquet'").fetchall())
    held = [(r.predicted, labels[r.doc_id]) for r in rows if r.held_out and labels.get(r.doc_id) is not None]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in rows)
    assert sum(p == y for p, y in held) / len(held) > 0.97 and sum(p > y for p, y in held) <= 0.01 * len(held)


def test_token_histogram(spark, texts):
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(tokens.default_tokenizer())
    n = [len(whole.encode(t, add_special_tokens=False).ids) + 1 for t in texts.values()]
    for r in run(spark, "op9_token_counts").collect():
        assert (r.n_docs, r.docs_within, r.docs_over) == (n.count(r.n_tokens), sum(x <= r.n_tokens for x in n), sum(x > r.n_tokens for x in n))
        assert (r.tokens_within, r.truncated_total, r.total_tokens) == (sum(x for x in n if x <= r.n_tokens), sum(min(x, r.n_tokens) for x in n), sum(n))


def test_html_against_the_article_element(spark):
    import html

    pages = dict(duckdb.sql(f"select page_id, html from '{DIR}/pages.parquet'").fetchall())
    for r in run(spark, "op10_html_extraction").collect():
        inner = re.search(r"<article>(.*?)(?:</article>|$)", pages[r.page_id], re.S)[1]
        blocks = [" ".join(html.unescape(re.sub("</?b>", "", b)).split()) for b in re.split(r"</?(?:p|h1|br)>", inner)]
        assert r.text == "\n".join(b for b in blocks if b) and r.n_chars == len(r.text)


@pytest.mark.parametrize("name", ["op6_chat_formatting", "op8_url_filters"])
def test_sql(spark, name):
    db = duckdb.connect()
    for t in ("conversations", "pages"):
        db.execute(f"create view {t} as select * from '{DIR}/{t}.parquet'")
    out = db.execute(queries.oracle_sql()[name])
    names = [c[0] for c in out.description]
    df = run(spark, name)
    assert sorted(df.columns) == sorted(names) and sorted(map(repr, (tuple(r) for r in df.select(names).collect()))) == sorted(map(repr, out.fetchall()))


def test_pipeline(spark):
    """Each stage's result follows from its own input, by plain Python."""
    docs = spark.read.parquet(f"{DIR}/documents.parquet")
    kept = docs
    for name, stage in corpus_pipeline.STAGES:
        before = {r.doc_id: r.text or "" for r in kept.collect()}
        out = corpus_pipeline.checkpointed(stage(spark, kept, DIR))
        if name == "near_duplicates":
            assert {r.doc_id for r in out.collect()} == {c for _, c in brute_components(before, 5).values()}
        elif name == "suffix_array":
            sizes = brute_repeats(before)
            assert all(abs(len(r.text.encode()) - (sizes[r.doc_id][0] - sizes[r.doc_id][1])) <= 6 * sizes[r.doc_id][2] for r in out.collect())
            assert {r.doc_id for r in out.collect()} == set(before)
        elif name == "packing":
            assert {r.doc_id for r in out.collect()} == set(before)
        kept = out
    assert sorted(map(repr, corpus_pipeline.run(spark, DIR).collect())) == sorted(map(repr, kept.collect()))
