"""Near-duplicates by MinHash bands, with sequential Bayesian verification and an exact check of what survives.

1. Every whole text becomes a set of word shingles, a MinHash signature and one key for each band of it.
2. Texts with equal sets form classes; only each class's least document goes on.
3. Documents that share a band key are candidates. A bucket is not expanded into pairs: its members are compared with a
   leader by their signatures, and what is far from the leader gets another one, until none is left. Documents that are not
   far apart so form families. Two documents above the threshold that share a bucket are in one family but for a chance
   that ``family_miss`` bounds.
4. In a family, links join documents into components. A pair is verified if it shares a band: signatures are compared batch by
   batch, and the pair is dropped once the posterior probability of the wanted similarity falls below the chosen miss
   probability; survivors are confirmed on their full sets, best first; pairs that links already join need none. A few
   members outside the largest component go first against all others, since most of a family of copies then joins it.
5. Of what is left, families with up to ``widest`` such strays are compared block against block; as that number is fixed, the
   rows that this takes are in proportion to the members. A family with more is one of texts that share a template and
   little else. There, pairs come from an exact prefix filter: two sets above the threshold share one of the first shingles of each, in an order that puts what
   is rare in the family first. Pages that share a template only have no such pair, so rows stay in proportion here too.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import wordhash as wh
from .components import ONE_TASK_EDGES, connected_components
from .storage import checkpointed, frugal


@dataclass(frozen=True)
class Settings:
    """A pair at exactly the threshold of 0.8 shares no band of 40 x 5 with probability 1.3e-7."""

    shingle: int = 5
    percent: int = 80
    bands: int = 40
    rows: int = 5
    batch: int = 40
    miss: float = 1e-7
    #: Shares of equal signature places: from ``near`` on two documents are one family; below ``far`` another leader is asked.
    near: float = 0.15
    far: float = 0.5

    @property
    def size(self) -> int:
        return self.bands * self.rows


def band_miss(s: Settings) -> float:
    """The chance that a pair at exactly the threshold shares no band; of a more similar pair it is smaller."""
    return (1 - (s.percent / 100) ** s.rows) ** s.bands


def family_miss(s: Settings) -> float:
    """A bound on the chance that two documents at the threshold, in one bucket, come into different families by one leader.

    One must agree with the leader in at least ``far`` of all places and the other in less than ``near``. At each place
    where only one agrees the two themselves differ, so they differ in more than far - near of the places, of which each
    differs with probability 1 - threshold at most.
    """
    d, least = 1 - s.percent / 100, math.floor((s.far - s.near) * s.size + 1e-9) + 1
    return sum(math.comb(s.size, k) * d**k * (1 - d) ** (s.size - k) for k in range(least, s.size + 1))


_rng = np.random.Generator(np.random.PCG64(7_351))
_ODD = _rng.integers(1, 2**63, 1024, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(1, 2**63, 1024, dtype=np.uint64)
#: Shingles that one pass over the permutations takes at once.
SLICE = 40_000


def signatures(h: np.ndarray, bounds: np.ndarray, size: int) -> np.ndarray:
    """MinHash signatures (upper 32 bits of each minimum) of rows of distinct shingle hashes; rows must not be empty."""
    out = np.empty((len(bounds) - 1, size), np.uint32)
    work = np.empty(len(h), np.uint64)
    for j in range(size):
        np.multiply(h, _ODD[j], out=work)
        np.add(work, _ADD[j], out=work)
        out[:, j] = np.minimum.reduceat(work, bounds[:-1]) >> np.uint64(32)
    return out


def band_keys(signature: np.ndarray, s: Settings) -> np.ndarray:
    """One 64-bit key for each band; the band's number is part of it."""
    keys = np.zeros((len(signature), s.bands), np.uint64)
    for j in range(s.rows):
        keys += signature[:, j :: s.rows][:, : s.bands].astype(np.uint64) * _ODD[900 + j]
    return wh.mix(keys + _ADD[900 : 900 + s.bands][None, :])


def _sets(column: pa.Array, shingle: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    for first, data, offsets in wh.byte_rows(column):
        words, bounds = wh.word_hashes(data, offsets)
        yield first, *wh.distinct_in_rows(*wh.shingle_hashes(words, bounds, shingle))


def _signed(h: np.ndarray, bounds: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """The rows with shingles, and their signatures; taken in slices that fit the processor's cache."""
    full = np.flatnonzero(np.diff(bounds))
    sig = np.empty((len(full), size), np.uint32)
    ends = bounds[full + 1]
    i = 0
    while i < len(full):
        j = max(int(np.searchsorted(ends, bounds[full[i]] + SLICE, side="right")), i + 1)
        a, b = bounds[full[i]], ends[j - 1]
        sig[i:j] = signatures(h[a:b], np.append(bounds[full[i:j]], b) - a, size)
        i = j
    return full, sig


def features(docs: DataFrame, s: Settings) -> DataFrame:
    """doc_id, n_shingles, two hashes of the set, and its band keys, which are null for texts without words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, h, bounds in _sets(batch.column(1), s.shingle):
                n = np.diff(bounds)
                one = wh.row_reduce(np.add, wh.mix(h ^ _ODD[1000]), bounds, 0).view(np.int64)
                two = wh.row_reduce(np.add, wh.mix(h + _ODD[1001]), bounds, 0).view(np.int64)
                full, sig = _signed(h, bounds, s.size)
                bands: list = [None] * len(n)
                for row, keys in zip(full.tolist(), band_keys(sig, s).view(np.int64), strict=True):
                    bands[row] = keys
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, len(n)), pa.array(n.astype(np.int64)), pa.array(one), pa.array(two), pa.array(bands, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "set1", "set2", "bands"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(frugal(run), "doc_id long, n_shingles long, set1 long, set2 long, bands array<long>")


def profiles(docs: DataFrame, s: Settings) -> DataFrame:
    """doc_id, signature, sketch (the low byte of each place of it) and hashes (the full set, sorted), all binary, of texts with words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, h, bounds in _sets(batch.column(1), s.shingle):
                full, sig = _signed(h, bounds, s.size)
                sets = [h[bounds[i] : bounds[i + 1]].tobytes() for i in full]
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(full + first)), pa.array([x.tobytes() for x in sig], pa.binary()), pa.array([x.tobytes() for x in sig.astype(np.uint8)], pa.binary()), pa.array(sets, pa.binary())], ["doc_id", "signature", "sketch", "hashes"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(frugal(run), "doc_id long, signature binary, sketch binary, hashes binary")


def least_matches(s: Settings) -> list[tuple[int, int]]:
    """(positions seen, fewest matches among them that keep a pair): below, P(similarity >= threshold | matches) < miss.

    The similarity has a uniform prior, so after m matches of k its posterior is Beta(m + 1, k - m + 1), whose upper tail
    from t is the chance that a binomial of k + 1 trials with probability t stays at or below m.
    """
    t, out = s.percent / 100, []
    for k in range(s.batch, s.size + 1, s.batch):
        tail, m = 0.0, -1
        while m < k:
            tail += math.comb(k + 1, m + 1) * t ** (m + 1) * (1 - t) ** (k - m)
            if tail >= s.miss:
                break
            m += 1
        out.append((k, m + 1))
    return out


def _estimates(pairs: DataFrame, known: DataFrame, s: Settings) -> DataFrame:
    """(a, b, near, far) of pairs (a, b): whether their sketches agree in enough places for one family, and in few enough to ask on.

    known: the candidates' profiles, laid out by doc_id, so that no join moves them all: pairs travel to b's profile, and of
    a's only those asked for are dealt anew, in a join that AQE may split where one document leads very many pairs.
    """
    leaders = known.join(pairs.select(F.col("a").alias("doc_id")).distinct(), "doc_id", "left_semi").select((F.col("doc_id") - F.lit(0)).alias("a"), F.col("sketch").alias("of_a"))
    both = known.select(F.col("doc_id").alias("b"), F.col("sketch").alias("of_b")).join(pairs, "b").join(leaders, "a").select("a", "b", "of_a", "of_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            left, right = (np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint8).reshape(-1, s.size) for i in (2, 3))
            share = (left == right).mean(axis=1)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(share >= s.near), pa.array(share < s.far)], ["a", "b", "near", "far"])

    return both.mapInArrow(frugal(run), "a long, b long, near boolean, far boolean")


def _families(shared: DataFrame, known: DataFrame, s: Settings) -> DataFrame:
    """(node, component): the family of every document that is near another one. shared: key, doc_id of buckets with two or more.

    Every member of a bucket is compared with the same leaders, in the first round one, later sixteen times as many each time;
    those far from all of them go on. Two documents above the threshold can only part if one is not far from a leader, and
    then the other is near it, but for the chance that ``family_miss`` bounds, so both are in its family.
    """
    edges, rest, leaders = None, shared, 1
    while True:
        sizes = rest.groupBy("key").agg(F.min("doc_id").alias("first"), F.count("*").alias("m")).where("m > 1")
        members = rest.join(sizes, "key")
        leading = (F.col("doc_id") == F.col("first")) | (F.pmod(F.xxhash64("doc_id", F.lit(leaders)), F.ceil(F.col("m") / leaders)) == 0) if leaders > 1 else F.col("doc_id") == F.col("first")
        members = checkpointed(members.select("key", "doc_id", leading.alias("leads")))
        asked = members.where("leads").select("key", F.col("doc_id").alias("a")).join(members.select("key", F.col("doc_id").alias("b"), "leads"), "key").where("a <> b and (not leads or a < b)")
        judged = checkpointed(_estimates(asked.select("a", "b").distinct(), known, s))
        found = judged.where("near").select(F.col("a").alias("u"), F.col("b").alias("v"))
        edges = found if edges is None else edges.union(found)
        settled = asked.where("not leads").join(judged.where("not far").select("a", "b"), ["a", "b"]).select("key", F.col("b").alias("doc_id"))
        rest = checkpointed(members.where("not leads").select("key", "doc_id").join(settled, ["key", "doc_id"], "left_anti"))
        if not rest.groupBy("key").count().where("count > 1").limit(1).count():
            return checkpointed(connected_components(edges, one_task_edges=ONE_TASK_EDGES))
        leaders *= 16


def _block_links(s: Settings):
    """(u, v) links between the queries and the targets of blocks; rows come ordered by block."""
    steps = least_matches(s)

    def solve(rows: list[tuple]) -> list[tuple[int, int]]:
        asking, asked = [r for r in rows if r[3]], [r for r in rows if not r[3]]
        if not asking or not asked:
            return []
        sets = [np.frombuffer(r[7], np.uint64) for r in asked]
        sizes = np.array([len(x) for x in sets])
        ids, roots = np.array([r[4] for r in asked]), np.array([r[5] for r in asked])
        # Targets that also ask in some block meet each pair twice; the one with the smaller query counts.
        strays = np.array([r[8] for r in asked])
        signs = np.frombuffer(b"".join(r[6] for r in asked), np.uint32).reshape(-1, s.size)
        parent: dict[int, int] = {}

        def root(c: int) -> int:
            while parent.get(c, c) != c:
                c = parent[c]
            return c

        out = []
        for _, _, _, _, doc, component, sign, hashes, _ in asking:
            x, own = np.frombuffer(hashes, np.uint64), np.frombuffer(sign, np.uint32)
            alive = np.flatnonzero((roots != component) & (np.minimum(sizes, len(x)) * 100 >= np.maximum(sizes, len(x)) * s.percent) & (~strays | (ids > doc)))
            matches, done = np.zeros(len(alive), np.int64), 0
            for k, least in steps:
                matches = matches + (signs[alive, done:k] == own[done:k]).sum(axis=1)
                keep = matches >= least
                alive, matches, done = alive[keep], matches[keep], k
            banded = (signs[alive] == own).reshape(-1, s.bands, s.rows).all(axis=2).any(axis=1)
            alive, matches = alive[banded], matches[banded]
            for i in alive[np.argsort(-matches, kind="stable")].tolist():
                here, there = root(component), root(int(roots[i]))
                if here == there:
                    continue
                y = sets[i]
                both = int((y[np.minimum(np.searchsorted(y, x), len(y) - 1)] == x).sum())
                if both * 100 >= s.percent * (len(x) + len(y) - both):
                    out.append((doc, int(ids[i])))
                    parent[here] = there
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block: list[tuple] = []
        for batch in batches:
            for row in zip(*(batch.column(i).to_pylist() for i in range(9)), strict=True):
                if block and block[-1][:3] != row[:3]:
                    found = solve(block)
                    block = []
                    if found:
                        yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found, strict=True)], ["u", "v"])
                block.append(row)
        found = solve(block)
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in zip(*found, strict=True)], ["u", "v"])

    return run


def _rare_first_pairs(placed: DataFrame, known: DataFrame, s: Settings, common_from: int = 32) -> DataFrame:
    """(a, b): pairs of a stray and another member of its family, in other components, whose prefixes share a shingle.

    placed: doc_id, family, c (component), stray. Shingles that ``common_from`` or more members of the family have come last in the order,
    the others first; both in the order of their hashes. Any order serves, if it is one for the whole family: a set above
    the threshold shares one of its first n - ceil(threshold * n) + 1 shingles with the other's.
    """

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [np.frombuffer(x, np.int64) for x in batch.column(2).to_pylist()]
            at = np.repeat(np.arange(len(sets)), [len(x) for x in sets])
            if len(at):
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(at)), batch.column(1).take(pa.array(at)), pa.array(np.concatenate(sets))], ["family", "doc_id", "h"])

    own = checkpointed(known.select("doc_id", "hashes").join(placed, "doc_id").select("family", "doc_id", "c", "stray", "hashes"))
    held = own.select("family", "doc_id", "hashes").mapInArrow(frugal(spread), "family long, doc_id long, h long")
    common = held.groupBy("family", "h").agg(F.count("*").alias("n")).where(F.col("n") >= common_from).select("family", "h")
    late = held.join(common, ["family", "h"]).groupBy("doc_id").agg(F.collect_list("h").alias("late"))

    def prefixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept, rows = [], []
            for i, (hashes, late) in enumerate(zip(batch.column(4).to_pylist(), batch.column(5).to_pylist(), strict=True)):
                x = np.frombuffer(hashes, np.int64)
                last = np.isin(x, np.array(late or [], np.int64))
                first = np.concatenate([x[~last], x[last]])[: len(x) - -(-s.percent * len(x) // 100) + 1]
                kept.append(first)
                rows += [(i, len(x))] * len(first)
            at = pa.array([r[0] for r in rows], pa.int32())
            yield pa.RecordBatch.from_arrays([*(batch.column(j).take(at) for j in range(4)), pa.array([r[1] for r in rows], pa.int64()), pa.array(np.concatenate(kept) if kept else np.zeros(0, np.int64))], ["family", "doc_id", "c", "stray", "n", "h"])

    first = own.join(late, "doc_id", "left").select("family", "doc_id", "c", "stray", "hashes", "late")
    first = checkpointed(first.mapInArrow(frugal(prefixes), "family long, doc_id long, c long, stray boolean, n long, h long"))
    mine = first.where("stray").select("family", "h", F.col("doc_id").alias("a"), F.col("c").alias("ca"), F.col("n").alias("na"))
    other = first.select("family", "h", F.col("doc_id").alias("b"), F.col("c").alias("cb"), F.col("n").alias("nb"), F.col("stray").alias("twice"))
    pairs = mine.join(other, ["family", "h"]).where("ca <> cb and (not twice or a < b)").where(F.least("na", "nb") * 100 >= F.greatest("na", "nb") * s.percent)
    return pairs.select("a", "b").distinct()


def _verified(pairs: DataFrame, known: DataFrame, s: Settings) -> DataFrame:
    """(u, v): the pairs (a, b) that pass the sequential test on their signatures and the exact one on their sets."""
    steps = least_matches(s)
    both = known.select(F.col("doc_id").alias("a"), F.col("signature").alias("sa"), F.col("hashes").alias("ha")).join(pairs, "a")
    both = both.join(known.select(F.col("doc_id").alias("b"), F.col("signature").alias("sb"), F.col("hashes").alias("hb")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for a, b, sa, sb, ha, hb in zip(*(batch.column(i).to_pylist() for i in range(6)), strict=True):
                same = np.frombuffer(sa, np.uint32) == np.frombuffer(sb, np.uint32)
                if all(int(same[:k].sum()) >= least for k, least in steps):
                    x, y = np.frombuffer(ha, np.uint64), np.frombuffer(hb, np.uint64)
                    shared = int((y[np.minimum(np.searchsorted(y, x), len(y) - 1)] == x).sum())
                    if shared * 100 >= s.percent * (len(x) + len(y) - shared):
                        out.append((a, b))
            yield pa.RecordBatch.from_arrays([pa.array([x[i] for x in out], pa.int64()) for i in (0, 1)], ["u", "v"])

    return both.select("a", "b", "sa", "sb", "ha", "hb").mapInArrow(frugal(run), "u long, v long")


def _block_pairs(rows: DataFrame, known: DataFrame, s: Settings, chunk: int) -> DataFrame:
    """(u, v): links of the members that ask with all others of their families, in blocks of about ``chunk`` on either side.

    rows: doc_id, family, c, asks, members (of the family), askers (of the family).
    """
    cut = lambda n: F.greatest(F.ceil(n / chunk), F.lit(1)).cast("long")
    rows = rows.withColumns({"down": cut(F.col("askers")), "across": cut(F.col("members"))})
    zero = F.lit(0).cast("long")
    target = rows.select("family", F.explode(F.sequence(zero, F.col("down") - 1)).alias("i"), F.pmod(F.xxhash64("doc_id", F.lit("t")), "across").alias("j"), F.lit(False).alias("query"), "doc_id", "c", F.col("asks").alias("twice"))
    query = rows.where("asks").select("family", F.pmod(F.xxhash64("doc_id", F.lit("q")), "down").alias("i"), F.explode(F.sequence(zero, F.col("across") - 1)).alias("j"), F.lit(True).alias("query"), "doc_id", "c", F.lit(False).alias("twice"))
    full = known.join(target.union(query), "doc_id").select("family", "i", "j", "query", "doc_id", "c", "signature", "hashes", "twice")
    return full.repartition("family", "i", "j").sortWithinPartitions("family", "i", "j", "query", "doc_id").mapInArrow(frugal(_block_links(s)), "u long, v long")


def _placed(families: DataFrame, components: DataFrame | None) -> DataFrame:
    """doc_id, family, c, stray (not in its family's largest component), members and strays of the family; whole families in one component go."""
    placed = families.select(F.col("node").alias("doc_id"), F.col("component").alias("family"))
    if components is None:
        placed = placed.withColumn("c", F.col("doc_id"))
    else:
        placed = placed.join(components, placed["doc_id"] == components["node"], "left").select("doc_id", "family", F.coalesce("component", "doc_id").alias("c"))
    sizes = placed.groupBy("family", "c").agg(F.count("*").alias("n"))
    sizes = sizes.groupBy("family").agg(F.sum("n").alias("members"), F.max(F.struct("n", "c")).alias("top"))
    sizes = sizes.select("family", "members", F.col("top.c").alias("largest"), (F.col("members") - F.col("top.n")).alias("strays")).where("strays > 0")
    return checkpointed(placed.join(sizes, "family").withColumn("stray", F.col("c") != F.col("largest")).drop("largest"))


def _links(families: DataFrame, known: DataFrame, s: Settings, asking: tuple[int, ...], chunk: int, widest: int) -> DataFrame | None:
    """(node, component) by links inside families: rounds ask about so many strays of each family, the last about all that are left.

    The first round is for all families, those between for families that still have more than ``widest`` strays.
    """
    links = components = placed = None
    for most in (*asking, None):
        placed = _placed(families, components) if placed is None else placed
        strays = placed.agg(F.max("strays")).first()[0]
        if strays is None:
            break
        if most and links is not None and strays <= widest:
            continue
        few = placed if links is None else placed.where(F.col("strays") > widest if most else F.col("strays") <= widest)
        every = F.ceil(F.col("strays") / most) if most else F.lit(1)
        few = few.withColumns({"asks": F.col("stray") & (F.pmod(F.xxhash64("doc_id", F.lit(most or 0)), every) == 0), "askers": F.least("strays", F.lit(most)) if most else F.col("strays")})
        more = checkpointed(_block_pairs(few, known, s, chunk))
        links = more if links is None else links.union(more)
        if most is None and strays > widest:
            wide = placed.where(F.col("strays") > widest).select("doc_id", "family", "c", "stray")
            links = links.union(checkpointed(_verified(_rare_first_pairs(wide, known, s), known, s)))
        components, placed = checkpointed(connected_components(links, one_task_edges=ONE_TASK_EDGES)), None
        if most and strays <= most:
            break
    return components


def near_duplicates(docs: DataFrame, settings: Settings = Settings(), asking: tuple[int, ...] = (64, 1024), chunk: int = 500, widest: int = 4096) -> DataFrame:  # noqa: B008
    """doc_id, n_shingles, component_id, kept, one row for each row of ``docs`` (doc_id, text).

    component_id is the least doc_id that links of similarity >= percent / 100 lead to; kept says that it is the row's own.
    Null, empty and blank texts have no shingles and no links. Rows that share a doc_id are taken for one document;
    a null doc_id has a null component and is kept, and other documents may not link through it.
    Further columns are ignored; an empty table gives no rows.
    """
    s = settings
    seen = checkpointed(features(docs, s))
    whole = seen.where(F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0))
    classes = whole.groupBy("set1", "set2").agg(F.min("doc_id").alias("rep"))
    member = whole.select("doc_id", "set1", "set2", "bands").join(classes, ["set1", "set2"]).where("doc_id = rep")
    slots = member.select("doc_id", F.explode("bands").alias("key"))
    buckets = slots.groupBy("key").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select("key")
    shared = checkpointed(slots.join(buckets, "key").distinct())
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).join(shared.select("doc_id").distinct(), "doc_id", "left_semi")
    known = checkpointed(profiles(texts, s).repartition(max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1), "doc_id"))
    components = _links(_families(shared, known, s), known, s, asking, chunk, widest)

    own = seen.select("doc_id", "n_shingles", "set1", "set2")
    placed = own.join(classes, (own["set1"] == classes["set1"]) & (own["set2"] == classes["set2"]) & (own["n_shingles"] > 0), "left").select("doc_id", "n_shingles", "rep")
    if components is None:
        placed = placed.withColumn("component", F.col("rep"))
    else:
        placed = placed.join(components, placed["rep"] == components["node"], "left")
    placed = placed.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "rep", "doc_id")).alias("component_id"))
    return placed.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, settings: Settings = Settings()) -> DataFrame:  # noqa: B008
    """``docs`` with one row of each group of near-duplicates, that of its least doc_id; columns as they were.

    Of several rows with that doc_id the one that sorts first by text, then by its other columns as JSON, stays; columns
    may be of any type, maps too. Rows without a doc_id stay.
    """
    kept = near_duplicates(docs, settings).where("kept and doc_id is not null").select("doc_id").distinct()
    whole = F.struct(*[docs[c] for c in docs.columns])
    rest = [docs[c] for c in docs.columns if c not in ("text", "doc_id")]
    order = F.struct(docs["text"], F.to_json(F.struct(*rest)) if rest else F.lit(""))
    ours = docs.select(F.col("doc_id"), whole.alias("row"), order.alias("order")).where("doc_id is not null").join(kept, "doc_id", "left_semi")
    return ours.groupBy("doc_id").agg(F.min_by("row", "order").alias("row")).select("row.*").union(docs.where("doc_id is null"))
