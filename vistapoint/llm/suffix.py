"""Removal of byte strings that occur more than once, decided by suffix arrays over candidate regions.

A corpus-wide suffix array would ship every suffix. Two exact steps keep it to what can repeat, and split it into blocks:

* Every window of ``length`` bytes owns one anchor, the least hash of its ``gram``-byte strings (leftmost on ties), so
  equal windows own equal anchors. Windows whose anchor occurs once cannot repeat and go no further.
* The windows of one anchor in one text are neighbours. Their bytes (a context) go to the block of that anchor.

In a block, two-stage sorting orders the suffixes: a suffix that is smaller than its successor is sorted directly, on
``length`` bytes; every other one is induced from its successor by one scan over the buckets of first bytes. Adjacent
common prefixes of at least ``length`` bytes then mark the repeated windows.

Equal texts are handled once, with their number. An anchor with more than ``hot`` occurrences (a passage in very many texts)
would make an unbounded block: its equal contexts are merged first, the others are dealt into parts that are sorted each
for itself, and the windows that a part leaves open are matched between parts by their fingerprints and then their bytes.
Equal whole texts and equal contexts are told by 128 bits of hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, IntegerType

from . import wordhash as wh
from .storage import checkpointed, frugal

LENGTH = 200
GRAM = 32
HOT = 4_000
#: Bytes of contexts that are sorted together; one anchor's contexts stay together beyond it.
BLOCK_BYTES = 1_000_000
#: Distinct contexts of a hot anchor that are sorted together, about.
PART_ROWS = 2_000
#: A run of equal bytes longer than this counts as smaller than its successor, so that contexts stay short.
RUN = 64

_BASE = 0xA24BAED4963EE407
_INVERSE = pow(_BASE, -1, 2**64)


def rolling(data: np.ndarray, size: int) -> np.ndarray:
    """Hashes of all strings of ``size`` bytes, by where they begin."""
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(wh.BYTE_CODES[data] * wh.powers(_BASE, len(data)), out=sums[1:])
    return wh.mix((sums[size:] - sums[:-size]) * wh.powers(_INVERSE, len(data))[: len(data) - size + 1])


def anchors(data: np.ndarray, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(anchor's hash, first window, last window) of every run of windows with the same anchor; places are in ``data``."""
    none = np.zeros(0, np.int64)
    if len(data) < length:
        return none.view(np.uint64), none, none
    grams = rolling(data, gram)
    span = length - gram + 1
    bits = np.uint64(int(len(data)).bit_length())
    keys = np.full(-(-len(grams) // span) * span, ~np.uint64(0), np.uint64)
    keys[: len(grams)] = ((grams >> bits) << bits) | np.arange(len(grams), dtype=np.uint64)
    laid = keys.reshape(-1, span)
    upto = np.minimum.accumulate(laid, axis=1).ravel()
    onto = np.minimum.accumulate(laid[:, ::-1], axis=1)[:, ::-1].ravel()
    least = np.minimum(onto[: len(data) - length + 1], upto[span - 1 : span - 1 + len(data) - length + 1])
    at = (least & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64)
    last = offsets[1:] - length
    n = np.maximum(last - offsets[:-1] + 1, 0)
    begins = np.cumsum(n) - n
    windows = np.arange(n.sum()) + np.repeat(offsets[:-1] - begins, n)
    if not len(windows):
        return none.view(np.uint64), none, none
    own = at[windows]
    cut = np.flatnonzero(np.concatenate([[True], (own[1:] != own[:-1]) | (windows[1:] != windows[:-1] + 1)]))
    return grams[own[cut]], windows[cut], windows[np.append(cut[1:], len(windows)) - 1]


def larger_than_successor(text: np.ndarray) -> np.ndarray:
    """Whether the suffix at each place is larger than the one after it, judged by the next RUN bytes."""
    step = text[1:].astype(np.int16) - text[:-1]
    place = np.arange(len(step))
    change = np.minimum.accumulate(np.where(step != 0, place, len(step))[::-1])[::-1]
    out = np.zeros(len(text), bool)
    near = (change - place < RUN) & (change < len(step))
    out[:-1][near] = step[change[near]] < 0
    return out


def two_stage_order(text: np.ndarray, bases: np.ndarray, counts: np.ndarray, length: int) -> np.ndarray:
    """The suffixes at bases[i] .. bases[i] + counts[i] - 1, sorted by their first ``length`` bytes.

    The last suffix of each run must be smaller than its successor (contexts are cut so).
    """
    places = np.arange(counts.sum()) + np.repeat(bases - (np.cumsum(counts) - counts), counts)
    larger = larger_than_successor(text)
    direct = places[~larger[places]]
    keys = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(text, length)[direct]).view(f"S{length}").ravel()
    direct = direct[np.argsort(keys, kind="stable")]
    del keys
    inducible = np.zeros(len(text) + 1, bool)
    inducible[places] = larger[places]
    heads = text[direct]
    letters = np.unique(text[places])
    starts, ends = np.searchsorted(heads, letters), np.searchsorted(heads, letters, side="right")
    waiting: dict[int, list[np.ndarray]] = {int(c): [] for c in letters}
    out = []
    for c, a, b in zip(letters.tolist(), starts.tolist(), ends.tolist(), strict=True):
        bucket = []
        front = np.concatenate(waiting.pop(c)) if waiting[c] else np.zeros(0, np.int64)
        while len(front):
            bucket.append(front)
            before = front - 1
            front = before[inducible[before] & (text[before] == c)]
        bucket.append(direct[a:b])
        whole = np.concatenate(bucket)
        out.append(whole)
        before = whole - 1
        before = before[inducible[before] & (text[before] > c)]
        if len(before):
            heads_before = text[before]
            order = np.argsort(heads_before, kind="stable")
            cuts = np.flatnonzero(np.diff(heads_before[order])) + 1
            for part in np.split(before[order], cuts):
                waiting[int(text[part[0]])].append(part)
    return np.concatenate(out) if out else np.zeros(0, np.int64)


def adjacent_prefixes(text: np.ndarray, order: np.ndarray, length: int) -> np.ndarray:
    """Lengths of the common prefixes of neighbours in ``order``, up to ``length``. text ends with length + 8 spare bytes."""
    words = np.ndarray((len(text) - 7,), "<u8", buffer=text, strides=(1,))
    out = np.full(max(len(order) - 1, 0), length, np.int64)
    alive = np.arange(len(out))
    for step in range(0, length, 8):
        differ = words[order[alive] + step] ^ words[order[alive + 1] + step]
        apart = differ != 0
        if apart.any():
            low = differ[apart]
            out[alive[apart]] = np.minimum(step + (np.log2((low & (~low + np.uint64(1))).astype(np.float64)) // 8).astype(np.int64), length)
            alive = alive[~apart]
    return out


def repeated_windows(contexts: list[bytes], windows: list[int], length: int) -> list[np.ndarray]:
    """For each context (its windows, their neighbours up to a suffix to sort directly, ``length`` bytes from there),
    which of its first ``windows[i]`` windows equal another window of the block."""
    text = np.frombuffer(b"".join(contexts) + bytes(length + RUN + 8), np.uint8)
    sizes = np.array([len(c) for c in contexts])
    bases = np.cumsum(sizes) - sizes
    n = np.array(windows)
    order = two_stage_order(text, bases, sizes - length + 1, length)
    real = np.zeros(len(text), bool)
    real[np.arange(n.sum()) + np.repeat(bases - (np.cumsum(n) - n), n)] = True
    order = order[real[order]]
    same = adjacent_prefixes(text, order, length) >= length
    hit = np.zeros(len(text), bool)
    hit[order[:-1][same]] = True
    hit[order[1:][same]] = True
    return [hit[a : a + k] for a, k in zip(bases.tolist(), windows, strict=True)]


def spans_of(mask: np.ndarray, starts: list[int], length: int) -> np.ndarray:
    """[begin, end) pairs, flat, of the bytes that the marked windows cover, for each place where the context stands."""
    edges = np.flatnonzero(np.diff(np.concatenate([[False], mask, [False]]).astype(np.int8)))
    pairs = edges.astype(np.int64)
    pairs[1::2] += length - 1
    return (np.asarray(starts, np.int64)[:, None] + pairs[None, :]).ravel()


def union(spans: np.ndarray) -> np.ndarray:
    """Flat [begin, end) pairs merged into maximal runs, in order."""
    if not len(spans):
        return spans
    pairs = spans.reshape(-1, 2)
    pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
    reach = np.maximum.accumulate(pairs[:, 1])
    first = np.concatenate([[True], pairs[1:, 0] > reach[:-1]])
    ends = reach[np.append(np.flatnonzero(first)[1:], len(pairs)) - 1]
    return np.stack([pairs[first, 0], ends], axis=1).ravel()


def _cut_contexts(length: int, gram: int):
    """Contexts of a text's candidate anchors; equal ones of a text are one row with all their places."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cold, hot = batch.column(4), batch.column(5)
            for first, data, offsets in wh.byte_rows(batch.column(3)):
                hashes, begin, end = anchors(data, offsets, length, gram)
                row = np.searchsorted(offsets, begin, side="right") - 1
                cuts = np.searchsorted(row, np.arange(len(offsets)))
                found: list[tuple] = []
                for i in range(len(offsets) - 1):
                    own = slice(cuts[i], cuts[i + 1])
                    few = np.asarray(cold[first + i].values.to_numpy(zero_copy_only=False), np.int64).view(np.uint64)
                    many = np.asarray(hot[first + i].values.to_numpy(zero_copy_only=False), np.int64).view(np.uint64)
                    is_hot = np.isin(hashes[own], many)
                    take = np.flatnonzero(is_hot | np.isin(hashes[own], few))
                    if not len(take):
                        continue
                    doc = np.concatenate([data[offsets[i] : offsets[i + 1]], np.zeros(length + RUN + 8, np.uint8)])
                    stop = np.where(larger_than_successor(doc), len(doc), np.arange(len(doc)))
                    stop = np.minimum.accumulate(stop[::-1])[::-1]
                    raw = doc.tobytes()
                    rows: dict[tuple, list] = {}
                    for j in take.tolist():
                        a, b = int(begin[own][j] - offsets[i]), int(end[own][j] - offsets[i])
                        key = (int(hashes[own][j].view(np.int64)), raw[a : int(stop[b]) + length])
                        rows.setdefault(key, [b - a + 1, bool(is_hot[j]), []])[2].append(a)
                    found += [(first + i, h, context, *rest) for (h, context), rest in rows.items()]
                if found:
                    at, h, context, n, is_hot, places = zip(*found, strict=True)
                    at = pa.array(at, pa.int32())
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).take(at), batch.column(1).take(at), batch.column(2).take(at), pa.array(h, pa.int64()), pa.array(context, pa.binary()), pa.array(n, pa.int32()), pa.array(is_hot, pa.bool_()), pa.array(places, pa.list_(pa.int32()))],
                        ["t1", "t2", "m", "h", "context", "windows", "is_hot", "places"],
                    )

    return run


_SPANS = "t1 long, t2 long, spans binary"


def _span_rows(found: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([x[i] for x in found], kind) for i, kind in enumerate((pa.int64(), pa.int64(), pa.binary()))], ["t1", "t2", "spans"])


def _sort_blocks(length: int, block_bytes: int):
    """Spans of repeated windows from contexts that come ordered by anchor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: list[tuple] = []
        held = 0

        def solved() -> pa.RecordBatch:
            found = []
            # An anchor that has one context here only, at one place of one text, repeats nowhere.
            masks = repeated_windows([x[4] for x in block], [x[5] for x in block], length)
            for (t1, t2, m, _, _, n, places), mask in zip(block, masks, strict=True):
                whole = np.ones(n, bool) if m * len(places) > 1 else mask
                if whole.any():
                    found.append((t1, t2, spans_of(whole, places, length).tobytes()))
            return _span_rows(found)

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(7)), strict=True):
                if held >= block_bytes and block[-1][3] != row[3]:
                    yield solved()
                    block, held = [], 0
                block.append(row)
                held += len(row[4])
        if block:
            yield solved()

    return run


def _hot_blocks(length: int, block_bytes: int):
    """For distinct contexts that come ordered by anchor and part: which windows are known to repeat, and the fingerprints
    of those that other parts must be asked about: all not yet known, and one of each of the known ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: list[tuple] = []
        held = 0

        def solved() -> pa.RecordBatch:
            masks = repeated_windows([x[6] for x in block], [x[4] for x in block], length)
            shown: set[tuple] = set()
            out: list[list] = [[], [], [], [], [], []]
            for (h, part, c1, c2, n, weight, context), mask in zip(block, masks, strict=True):
                known = np.ones(n, bool) if weight > 1 else mask
                prints = rolling(np.frombuffer(context, np.uint8)[: n + length - 1], length).view(np.int64)
                ask = ~known
                for i in np.flatnonzero(known).tolist():
                    one = (h, part, int(prints[i]))
                    if one not in shown:
                        shown.add(one)
                        ask[i] = True
                at = np.flatnonzero(ask).astype(np.int32)
                for column, value in zip(out, (h, c1, c2, known.tobytes(), at, prints[at]), strict=True):
                    column.append(value)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.list_(pa.int32()), pa.list_(pa.int64()))
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(out, kinds, strict=True)], ["h", "c1", "c2", "known", "at", "print"])

        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(7)), strict=True):
                if held >= block_bytes and block[-1][:2] != row[:2]:
                    yield solved()
                    block, held = [], 0
                block.append(row)
                held += len(row[6])
        if block:
            yield solved()

    return run


def _hot_spans(contexts: DataFrame, length: int, block_bytes: int, part_rows: int) -> DataFrame:
    """Spans for contexts of anchors that occur very often.

    Equal contexts are merged; the others of an anchor are dealt into parts of about ``part_rows``, each sorted by itself;
    what a part leaves open is matched between parts by fingerprints, and what matches is compared byte for byte.
    """
    own = contexts.withColumns({"c1": F.xxhash64("context"), "c2": F.xxhash64(F.lit(1), "context"), "weight": F.col("m") * F.size("places")})
    distinct = checkpointed(own.groupBy("h", "c1", "c2").agg(F.sum("weight").alias("weight")))
    parts = distinct.groupBy("h").agg(F.ceil(F.count("*") / part_rows).alias("parts"))
    texts = own.select("h", "c1", "c2", "windows", "context").dropDuplicates(["h", "c1", "c2"])
    dealt = texts.join(distinct, ["h", "c1", "c2"]).join(parts, "h").select("h", F.pmod("c1", "parts").alias("part"), "c1", "c2", "windows", "weight", "context")
    dealt = dealt.repartition("h", "part").sortWithinPartitions("h", "part")
    solved = checkpointed(dealt.mapInArrow(frugal(_hot_blocks(length, block_bytes)), "h long, c1 long, c2 long, known binary, at array<int>, print array<long>"))
    asked = solved.select("h", "c1", "c2", F.explode(F.arrays_zip("at", "print")).alias("x")).select("h", "c1", "c2", "x.at", "x.print")
    twice = asked.groupBy("h", "print").agg(F.count("*").alias("n")).where("n > 1").drop("n")
    alike = asked.join(twice, ["h", "print"], "left_semi").groupBy("h", "c1", "c2").agg(F.collect_list("at").alias("places"))

    def windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for h, c1, c2, context, places in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
                values = ([h] * len(places), [c1] * len(places), [c2] * len(places), places, [context[i : i + length] for i in places])
                yield pa.RecordBatch.from_arrays([pa.array(v, k) for v, k in zip(values, kinds, strict=True)], ["h", "c1", "c2", "at", "window"])

    shown = checkpointed(texts.join(alike, ["h", "c1", "c2"]).select("h", "c1", "c2", "context", "places").mapInArrow(frugal(windows), "h long, c1 long, c2 long, at int, window binary"))
    same = shown.groupBy("h", "window").agg(F.count("*").alias("n")).where("n > 1").drop("n")
    more = shown.join(same, ["h", "window"], "left_semi").groupBy("h", "c1", "c2").agg(F.collect_list("at").alias("more"))
    verdict = solved.select("h", "c1", "c2", "known").join(more, ["h", "c1", "c2"], "left")

    def spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for t1, t2, places, known, more in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
                mask = np.frombuffer(known, bool).copy()
                mask[more or []] = True
                if mask.any():
                    found.append((t1, t2, spans_of(mask, places, length).tobytes()))
            yield _span_rows(found)

    return own.select("t1", "t2", "places", "h", "c1", "c2").join(verdict, ["h", "c1", "c2"]).select("t1", "t2", "places", "known", "more").mapInArrow(frugal(spans), _SPANS)


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT, block_bytes: int = BLOCK_BYTES, part_rows: int = PART_ROWS) -> DataFrame:
    """``docs`` (doc_id, text, ...) with n_bytes, n_removed, n_spans, removed (flat [begin, end) pairs in bytes), kept (binary)
    and kept_text (the same as text, without the parts of characters that a cut went through).

    A byte goes if a string of ``length`` bytes that covers it also begins anywhere else, in this text or another; strings
    are judged on the input. Null texts count as empty. Repeated rows are copies of each other. Other columns pass through;
    columns with the names added here are replaced. ``length`` is a multiple of 8 and larger than ``gram``.
    """
    if length % 8 or not RUN < length or not 0 < gram < length:
        raise ValueError("length must be a multiple of 8 above 64 and larger than gram")
    added = ("n_bytes", "n_removed", "n_spans", "removed", "kept", "kept_text")
    names = [c for c in docs.columns if c not in added]
    text = F.coalesce(docs["text"].cast("string"), F.lit(""))
    keyed = docs.select(F.xxhash64(text).alias("t1"), F.xxhash64(F.lit(1), text).alias("t2"), F.coalesce(docs["doc_id"].cast("long"), F.lit(-(2**63))).alias("own"), text.alias("text"))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, data, offsets in wh.byte_rows(batch.column(3)):
                n = len(offsets) - 1
                hashes, begin, _ = anchors(data, offsets, length, gram)
                row = np.searchsorted(offsets, begin, side="right") - 1
                cuts = np.searchsorted(row, np.arange(n + 1))
                once, often = [], []
                for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                    values, counts = np.unique(hashes[a:b], return_counts=True)
                    once.append(values[counts == 1].view(np.int64))
                    often.append(values[counts > 1].view(np.int64))
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(first, n) for i in range(3)), pa.array(np.diff(offsets)), pa.array(once, pa.list_(pa.int64())), pa.array(often, pa.list_(pa.int64()))], ["t1", "t2", "own", "n_bytes", "once", "often"])

    known = checkpointed(keyed.mapInArrow(frugal(scan), "t1 long, t2 long, own long, n_bytes long, once array<long>, often array<long>"))
    texts = known.where(F.col("n_bytes") >= length).groupBy("t1", "t2").agg(F.min("own").alias("rep"), F.count("*").alias("m"), F.max("n_bytes").alias("size"))
    texts = checkpointed(texts)
    firsts = known.join(texts, ["t1", "t2"]).where("own = rep").select("t1", "t2", "m", "once", "often")
    seen = firsts.select("t1", "t2", "m", F.explode("once").alias("h")).union(firsts.select("t1", "t2", (F.col("m") * 2).alias("m"), F.explode("often").alias("h")))
    counts = seen.groupBy("h").agg(F.sum("m").alias("total")).where("total > 1")
    wanted = seen.select("t1", "t2", "h").join(counts, "h").groupBy("t1", "t2").agg(F.collect_list(F.when(F.col("total") <= hot, F.col("h"))).alias("cold"), F.collect_list(F.when(F.col("total") > hot, F.col("h"))).alias("hot"))
    wanted = wanted.join(texts, ["t1", "t2"])
    sources = keyed.join(wanted, ["t1", "t2"]).where("own = rep").select("t1", "t2", "m", "text", "cold", "hot")
    contexts = checkpointed(sources.mapInArrow(frugal(_cut_contexts(length, gram)), "t1 long, t2 long, m long, h long, context binary, windows int, is_hot boolean, places array<int>"))
    sorted_blocks = contexts.where("not is_hot").select("t1", "t2", "m", "h", "context", "windows", "places").repartition("h").sortWithinPartitions("h")
    spans = sorted_blocks.mapInArrow(frugal(_sort_blocks(length, block_bytes)), _SPANS)
    if contexts.where("is_hot").limit(1).count():
        spans = spans.union(_hot_spans(contexts.where("is_hot"), length, block_bytes, part_rows))
    spans = spans.groupBy("t1", "t2").agg(F.collect_list("spans").alias("spans"))
    copies = texts.where("m > 1").select("t1", "t2", F.lit(True).alias("copied"))
    verdicts = spans.join(copies, ["t1", "t2"], "full_outer").select(F.col("t1").alias("__t1"), F.col("t2").alias("__t2"), F.col("spans").alias("__spans"), F.coalesce("copied", F.lit(False)).alias("__copied"))

    whole = docs.select(*[docs[c] for c in names], F.xxhash64(text).alias("__k1"), F.xxhash64(F.lit(1), text).alias("__k2"), text.alias("__text"))
    joined = whole.join(verdicts, (F.col("__k1") == F.col("__t1")) & (F.col("__k2") == F.col("__t2")), "left").select(*[F.col(f"`{c}`") for c in names], "__text", "__spans", "__copied")
    schema = docs.select([docs[c] for c in names]).schema.add("n_bytes", "long").add("n_removed", "long").add("n_spans", "long").add("removed", ArrayType(IntegerType())).add("kept", "binary").add("kept_text", "string")
    place = len(names)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            columns: list[list] = [[] for _ in added]
            for text, spans, copied in zip(batch.column(place).to_pylist(), batch.column(place + 1).to_pylist(), batch.column(place + 2).to_pylist(), strict=True):
                raw = text.encode()
                if copied and len(raw) >= length:
                    gone = np.array([0, len(raw)])
                else:
                    gone = union(np.concatenate([np.frombuffer(x, np.int64) for x in spans])) if spans else np.zeros(0, np.int64)
                edges = [0, *gone.tolist(), len(raw)]
                pieces = [raw[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)]
                left = b"".join(pieces)
                shown = "".join(x.decode(errors="ignore") for x in pieces)
                for column, value in zip(columns, (len(raw), len(raw) - len(left), len(gone) // 2, gone.astype(np.int32), left, shown), strict=True):
                    column.append(value)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.int32()), pa.binary(), pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns[:place], *(pa.array(c, k) for c, k in zip(columns, kinds, strict=True))], [*batch.schema.names[:place], *added])

    return joined.mapInArrow(frugal(cut), schema)
