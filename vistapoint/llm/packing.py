"""Hierarchical packing of documents into windows of several lengths, with no token lost and next to no padding.

Every partition packs its own documents, block by block, so nothing is shuffled and memory is bounded by a block.
A document is routed to the tier of the smallest window that holds it (what exceeds the longest window fills whole
windows first). Windows are filled from the longest tier down: the longest piece opens a window of its tier, the gap is
filled with the largest pieces of the same or shorter tiers that fit, and when none fits, one is cut to close the gap.
A block's unfilled window returns to the next block; at the end of the partition the last one is split into windows
whose lengths are powers of two, so that it needs no padding either. Windows of one tier form step groups of up to the
wanted token count, of which a tier's groups differ by one window at most; the closing windows of a partition have lengths
of their own, so their groups hold less. The cost of attention (sum of squared piece lengths) is balanced by dealing windows out in a snake.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .storage import frugal
from .tokens import default_tokenizer, encoder

TIERS = (256, 512, 1024, 2048)
BLOCK_TOKENS = 2_000_000
STEP_TOKENS = 16_384
#: Rows of an Arrow batch whose texts are Python strings at once.
ROWS_AT_ONCE = 100
#: Sequence ids of one partition begin at its number times this.
SEQUENCES_PER_PARTITION = 1 << 36

SCHEMA = "doc_id long, start long, length long, ids binary, doc_tokens long, sequence_id long, offset long, tier int, step_group long"
_ARROW = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids", pa.binary()), ("doc_tokens", pa.int64()), ("sequence_id", pa.int64()), ("offset", pa.int64()), ("tier", pa.int32()), ("step_group", pa.int64())])

Piece = tuple[int, int, int]  # document's place in the block, first id, number of ids


class _Pool:
    """Pieces by length; the set of lengths present is one integer's bits, so the largest that fits is found at once."""

    def __init__(self) -> None:
        self.by_length: dict[int, list[Piece]] = {}
        self.present = 0
        self.tokens = 0

    def add(self, piece: Piece) -> None:
        self.by_length.setdefault(piece[2], []).append(piece)
        self.present |= 1 << piece[2]
        self.tokens += piece[2]

    def take(self, length: int) -> Piece:
        pieces = self.by_length[length]
        piece = pieces.pop()
        if not pieces:
            del self.by_length[length]
            self.present ^= 1 << length
        self.tokens -= length
        return piece

    def longest(self, most: int) -> int:
        """The largest length present of at most ``most``, or 0."""
        return max((self.present & ((1 << (most + 1)) - 1)).bit_length() - 1, 0)

    def shortest(self) -> int:
        return (self.present & -self.present).bit_length() - 1


def pack_block(pool: _Pool, tiers: tuple[int, ...]) -> Iterator[tuple[int, list[Piece]]]:
    """(tier, pieces) of full windows; what cannot fill a window stays in the pool."""
    top = tiers[-1]
    while pool.present:
        first = pool.longest(top)
        tier = next(t for t in tiers if t >= first)
        if pool.tokens < tier:
            return
        window = [pool.take(first)]
        gap = tier - first
        while gap:
            fits = pool.longest(gap)
            if fits:
                window.append(pool.take(fits))
                gap -= fits
            else:
                doc, start, length = pool.take(pool.shortest())
                window.append((doc, start, gap))
                pool.add((doc, start + gap, length - gap))
                gap = 0
        yield tier, window


def closing_windows(pieces: list[Piece]) -> Iterator[tuple[int, list[Piece]]]:
    """Windows of falling powers of two that hold exactly these pieces."""
    rest, left = sum(p[2] for p in pieces), list(reversed(pieces))
    while rest:
        tier = 1 << (rest.bit_length() - 1)
        window, gap = [], tier
        while gap:
            doc, start, length = left.pop()
            taken = min(gap, length)
            window.append((doc, start, taken))
            if taken < length:
                left.append((doc, start + taken, length - taken))
            gap -= taken
        rest -= tier
        yield tier, window


def step_groups(windows: list[tuple[int, list[Piece]]], step_tokens: int) -> list[int]:
    """A group for each window: windows of one tier only, as even in number as can be, at most ``step_tokens`` each, attention cost balanced by a snake deal."""
    out, base = [0] * len(windows), 0
    by_tier: dict[int, list[tuple[int, int]]] = {}
    for i, (tier, pieces) in enumerate(windows):
        by_tier.setdefault(tier, []).append((-sum(p[2] ** 2 for p in pieces), i))
    for tier in sorted(by_tier, reverse=True):
        ranked = sorted(by_tier[tier])
        groups = -(-len(ranked) * tier // step_tokens)
        for rank, (_, i) in enumerate(ranked):
            lap, place = divmod(rank, groups)
            out[i] = base + (place if lap % 2 == 0 else groups - 1 - place)
        base += groups
    return out


def pack(
    docs: DataFrame, tokenizer: str | None = None, tiers: tuple[int, ...] = TIERS, end_id: int = 1, block_tokens: int = BLOCK_TOKENS, step_tokens: int = STEP_TOKENS
) -> DataFrame:
    """Pack every document of ``docs`` (doc_id, text) into windows; one row per piece with its ids (binary, little-endian
    unsigned 32-bit), doc_tokens, its place (sequence_id, offset), the window's length (tier) and its step_group.

    Null and empty texts are the end id alone. A null doc_id stays null. Repeated rows are packed each for itself; further
    columns are ignored; an empty table gives no row. ``tiers`` are powers of two in rising order. Rows of one partition
    are packed in the order in which they come, so ``docs`` should be read from files, whose order a rerun repeats.
    """
    if list(tiers) != sorted(set(tiers)) or any(t < 1 or t & (t - 1) for t in tiers):
        raise ValueError("tiers are rising powers of two")
    path, top = tokenizer or default_tokenizer(), tiers[-1]
    end = end_id.to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path).encode
        context = TaskContext.get()
        sequence = (context.partitionId() if context else 0) * SEQUENCES_PER_PARTITION
        group = sequence
        pool, ids, names = _Pool(), {}, {}
        count = 0

        def emitted(windows: list[tuple[int, list[Piece]]]) -> Iterator[pa.RecordBatch]:
            nonlocal sequence, group
            groups = step_groups(windows, step_tokens)
            columns: list[list] = [[] for _ in _ARROW]
            for (tier, pieces), own in zip(windows, groups, strict=True):
                offset = 0
                for doc, start, length in pieces:
                    for column, value in zip(columns, (names[doc], start, length, ids[doc][4 * start : 4 * (start + length)], len(ids[doc]) // 4, sequence, offset, tier, group + own), strict=True):
                        column.append(value)
                    offset += length
                sequence += 1
                if len(columns[0]) >= 20_000:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, _ARROW, strict=True)], schema=_ARROW)
                    columns = [[] for _ in _ARROW]
            if columns[0]:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, _ARROW, strict=True)], schema=_ARROW)
            group += max(groups, default=-1) + 1

        full: list[tuple[int, list[Piece]]] = []
        held = 0

        def flush() -> Iterator[pa.RecordBatch]:
            nonlocal full, held
            full += pack_block(pool, tiers)
            yield from emitted(full)
            full = []
            waiting = {p[0] for pieces in pool.by_length.values() for p in pieces}
            for doc in [d for d in ids if d not in waiting]:
                del ids[doc], names[doc]
            held = sum(len(x) // 4 for x in ids.values())

        def rows(batch: pa.RecordBatch) -> Iterator[tuple]:
            """The rows of a batch, of which few at a time are Python strings."""
            for at in range(0, batch.num_rows, ROWS_AT_ONCE):
                some = batch.slice(at, ROWS_AT_ONCE)
                yield from zip(some.column(0).to_pylist(), some.column(1).to_pylist(), strict=True)

        for batch in batches:
            for name, text in rows(batch):
                encoded = (encode(text) if text else b"") + end
                n = len(encoded) // 4
                ids[count], names[count] = encoded, name
                whole = n // top
                full += [(top, [(count, i * top, top)]) for i in range(whole)]
                if n % top:
                    pool.add((count, whole * top, n % top))
                count += 1
                held += n
                if held >= block_tokens:
                    yield from flush()
        yield from flush()
        rest = [p for _, pieces in sorted(pool.by_length.items(), reverse=True) for p in pieces]
        yield from emitted(list(closing_windows(rest)))

    return docs.select("doc_id", docs["text"].cast("string")).mapInArrow(frugal(run, keep_words=True), SCHEMA)


