"""Benchmark decontamination: item-sized windows by SimHash, found through a multi-index, confirmed by weighted shingles.

1. A window of an item's size reaches the wanted similarity only if it holds one of the item's leading shingles, the rarest
   ones that together weigh more than what may be missing. One pass over all texts finds the documents that hold any.
2. In these, windows of the item's size are cut at every place where a shared shingle begins and enough shared weight
   follows. That is enough: a window that begins elsewhere can be moved on to its first shared shingle, by which it loses
   only places without shared shingles and gains as many at most, so it is not less similar. Windows that stick out over
   the text's beginning are cut where a shared shingle ends, which in the same way loses nothing.
3. Every window and every item gets a 64-bit SimHash of its words and word pairs. The fingerprint is cut into blocks; two
   fingerprints within the radius agree, up to radius // blocks bits, in one block. Each item is entered under every value
   so near to its own in a block, so equal block values find all items within the radius of a window, whichever item it was cut for.
4. Candidates within the radius are confirmed by the exact weighted similarity of their shingles, in which an item's
   shingles weigh more the fewer items have them, and every place of the window with another shingle counts against it.

Only DataFrame and SQL functions are used. Words are runs of letters and digits, lower-cased.
"""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .quality import let
from .storage import checkpointed

SHINGLE = 5
SIMILARITY = 0.8
RADIUS = 15
BLOCKS = 4
#: What sums of weights may be off by through the order of additions.
SLACK = 1e-9
#: Item shingles that are broadcast at once; more are taken in so many blocks, each in a pass of its own over the texts.
BROADCAST_SHINGLES = 1_000_000
#: Documents up to this number are picked out of all by a broadcast of their ids, more by a shuffle.
BROADCAST_DOCS = 1_000_000


def words_of(text: Column) -> Column:
    plain = F.btrim(F.regexp_replace(F.lower(F.coalesce(text.cast("string"), F.lit(""))), r"[^\p{L}\p{N}]+", " "))
    return F.when(plain == "", F.expr("cast(array() as array<string>)")).otherwise(F.split(plain, " ", -1))


def shingles(words: Column, size: int) -> Column:
    """Hashes of every run of ``size`` words; fewer words are one shingle, none are none."""
    runs = F.transform(F.sequence(F.lit(0), F.size(words) - size), lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(size)]))
    return F.when(F.size(words) >= size, runs).when(F.size(words) > 0, F.array(F.xxhash64(F.array_join(words, " ")))).otherwise(F.expr("cast(array() as array<bigint>)"))


def simhash(words: Column) -> Column:
    """64 bits: each is set if most hashes of the words and of neighbouring pairs have it set."""
    singles = F.transform(words, lambda w: F.xxhash64(w))
    pairs = F.transform(words, lambda w, i: F.xxhash64(w, F.get(words, i + 1)))

    def bits(hashes: Column) -> Column:
        def bit(b: Column) -> Column:
            ones = F.aggregate(hashes, F.lit(0), lambda n, h: n + F.getbit(h, b).cast("int"))
            return F.when(ones * 2 > F.size(hashes), F.lit(1).cast("long")).otherwise(F.lit(0).cast("long"))

        return F.aggregate(F.sequence(F.lit(0), F.lit(63)), F.lit(0).cast("long"), lambda x, b: F.shiftleft(x, 1).bitwiseOR(bit(b)))

    return let(F.concat(singles, pairs), bits)


def block_value(fingerprint: Column, block: int, blocks: int) -> Column:
    width = 64 // blocks
    return F.shiftrightunsigned(fingerprint, block * width).bitwiseAND(F.lit((1 << width) - 1).cast("long"))


def _items(benchmark: DataFrame, size: int, similarity: float) -> tuple[DataFrame, DataFrame]:
    """(items, names). items, one for each distinct wording: item, n (words), places (shingle hashes in order), weights (of each
    distinct one), whole (their sum), foreign (the weight of any other shingle), fingerprint, leading (shingles of which a
    similar window holds one). names: item, item_id."""
    split = benchmark.select("item_id", words_of(F.col("text")).alias("words")).where(F.size("words") > 0)
    split = split.withColumns({"c1": F.xxhash64("words"), "c2": F.xxhash64(F.lit(1), "words")})
    first = split.groupBy("c1", "c2").agg(F.first("words").alias("words")).withColumn("item", F.xxhash64("c1", "c2"))
    items = checkpointed(first.select("item", "c1", "c2", F.size("words").alias("n"), shingles(F.col("words"), size).alias("places"), simhash(F.col("words")).alias("fingerprint")))
    total = F.lit(float(items.count()))
    each = items.select("item", F.explode(F.array_distinct("places")).alias("h"))
    rare = each.groupBy("h").agg(F.count("*").alias("df")).select("h", (1 + F.log(total / F.col("df"))).alias("w"))
    weights = each.join(rare, "h").groupBy("item").agg(F.map_from_entries(F.collect_list(F.struct("h", "w"))).alias("weights"))
    known = items.drop("c1", "c2").join(weights, "item").withColumns({"foreign": 1 + F.log(total + 1), "whole": _mass(F.map_values("weights"))})
    ranked = F.sort_array(F.transform(F.map_entries("weights"), lambda e: F.struct((-e["value"]).alias("w"), e["key"].alias("h"))))
    start = F.struct(F.lit(0.0).alias("sum"), F.expr("cast(array() as array<bigint>)").alias("hs"))
    enough = F.col("whole") * (1 - similarity) + SLACK
    lead = F.aggregate(ranked, start, lambda s, e: F.when(s["sum"] > enough, s).otherwise(F.struct((s["sum"] - e["w"]).alias("sum"), F.array_append(s["hs"], e["h"]).alias("hs"))), lambda s: s["hs"])
    known = checkpointed(known.withColumn("leading", lead))
    return known, split.join(items.select("item", "c1", "c2"), ["c1", "c2"]).select("item", "item_id").distinct()


def _mass(weights: Column) -> Column:
    return F.aggregate(weights, F.lit(0.0), lambda s, x: s + x)


def _in_blocks(places: DataFrame, known: DataFrame, columns: list[str]) -> DataFrame:
    """``places`` joined with ``known`` on h; known is broadcast block by block, so that places are never shuffled."""
    blocks = max(-(-known.count() // BROADCAST_SHINGLES), 1)
    out = None
    for i in range(blocks):
        part = known if blocks == 1 else known.where(F.pmod(F.xxhash64("h", F.lit("block")), F.lit(blocks)) == i)
        found = places.join(F.broadcast(part), "h").select(*columns)
        out = found if out is None else out.union(found)
    return out


def windows_of(keyed: DataFrame, items: DataFrame, size: int, similarity: float) -> DataFrame:
    """doc_id, key, start, n, words: windows of the items' sizes in all documents where a similarity may be reached."""
    places = keyed.select("doc_id", "key", F.explode(let(words_of(F.col("text")), lambda w: shingles(w, size))).alias("h"))
    leading = checkpointed(items.select("item", F.explode("leading").alias("h")))
    asked = checkpointed(_in_blocks(places, leading, ["doc_id", "key", "item"]).distinct())
    own = asked.select(F.col("doc_id").alias("own"), F.col("key").alias("own_key")).distinct()
    few = own.limit(BROADCAST_DOCS + 1).count() <= BROADCAST_DOCS
    found = keyed.join(F.broadcast(own) if few else own, (F.col("key") == F.col("own_key")) & F.col("doc_id").eqNullSafe(F.col("own")), "left_semi")
    found = checkpointed(found.dropDuplicates(["doc_id", "key"]).select("doc_id", "key", words_of(F.col("text")).alias("words")))

    weighed = checkpointed(items.select("item", "n", "whole", F.explode("weights").alias("h", "w")))
    shared = _in_blocks(found.select("doc_id", "key", F.posexplode(shingles(F.col("words"), size)).alias("place", "h")), weighed, ["doc_id", "key", "item", "n", "whole", "place", "w"])
    pairs = asked.withColumnsRenamed({"doc_id": "own", "key": "own_key", "item": "own_item"})
    shared = shared.join(pairs, (F.col("key") == F.col("own_key")) & (F.col("item") == F.col("own_item")) & F.col("doc_id").eqNullSafe(F.col("own")), "left_semi")
    lists = shared.groupBy("doc_id", "key", "item", "n", "whole").agg(F.sort_array(F.collect_list(F.struct("place", "w"))).alias("at"))
    reach = F.greatest(F.col("n") - size, F.lit(0))

    def follows(x: Column, i: Column) -> Column:
        """The shared weight from a place on, as far as a window that begins there goes; repeated shingles count each time."""
        ahead = F.slice("at", i + 1, reach + 1)
        return F.aggregate(ahead, F.lit(0.0), lambda s, y: s + F.when(y["place"] <= x["place"] + reach, y["w"]).otherwise(0.0))

    least = F.col("whole") * similarity - SLACK
    piece = lambda start, length: F.struct(start.cast("int").alias("start"), length.cast("int").alias("length"))
    inside = F.transform("at", lambda x, i: F.when(follows(x, i) >= least, piece(x["place"], F.col("n"))))
    before = lambda i: F.aggregate(F.slice("at", 1, i + 1), F.lit(0.0), lambda s, y: s + y["w"])
    heads = F.transform(F.slice("at", 1, F.col("n")), lambda x, i: F.when((x["place"] + size < F.col("n")) & (before(i) >= least), piece(F.lit(0), x["place"] + size)))
    pieces = F.filter(F.concat(inside, heads), lambda x: x.isNotNull())
    starts = lists.select("doc_id", "key", "n", F.explode(pieces).alias("piece")).select("doc_id", "key", "n", "piece.start", "piece.length").distinct()
    starts = starts.withColumnsRenamed({"doc_id": "own", "key": "own_key"})
    cut = found.join(starts, (F.col("key") == F.col("own_key")) & F.col("doc_id").eqNullSafe(F.col("own")))
    return cut.select("doc_id", "key", "start", "n", F.slice("words", F.col("start") + 1, F.col("length")).alias("words"))


def leaks(docs: DataFrame, benchmark: DataFrame, size: int = SHINGLE, similarity: float = SIMILARITY, radius: int = RADIUS, blocks: int = BLOCKS) -> DataFrame:
    """doc_id, item_id, start (word), n_words, distance (bits), similarity: the best window of each document for each leaked item.

    docs: doc_id, text; benchmark: item_id, text. Null, empty and wordless texts leak nothing. Windows are clipped at a
    document's ends. Repeated rows give one row. A null doc_id is reported as such. Items of fewer than ``size`` words
    match only documents that consist of those words. Further columns are ignored; an empty table on either side gives no rows.
    """
    if 64 % blocks or radius < 0 or not 0 < similarity <= 1:
        raise ValueError("blocks must divide 64, and similarity lies in (0, 1]")
    items, names = _items(benchmark, size, similarity)
    text = docs["text"].cast("string")
    keyed = docs.select("doc_id", F.xxhash64(text).alias("key"), text.alias("text"))
    windows = windows_of(keyed, items, size, similarity)
    windows = checkpointed(windows.withColumns({"c1": F.xxhash64("words"), "c2": F.xxhash64(F.lit(1), "words")}))

    # Equal windows, such as those of a passage in very many documents, are fingerprinted and confirmed once.
    distinct = windows.groupBy("c1", "c2", "n").agg(F.first("words").alias("words"))
    prints = checkpointed(distinct.select("c1", "c2", F.col("n").alias("own_n"), shingles(F.col("words"), size).alias("own_places"), simhash(F.col("words")).alias("own_print")))
    width = 64 // blocks
    masks = [sum(1 << b for b in bits) for k in range(radius // blocks + 1) for bits in combinations(range(width), k)]
    entry = lambda f: F.array(*[F.struct(F.lit(b).alias("block"), block_value(f, b, blocks).alias("value")) for b in range(blocks)])
    index = items.select("item", "n", "fingerprint", F.explode(entry(F.col("fingerprint"))).alias("e")).select("item", "n", "fingerprint", "e.block", "e.value")
    near = F.transform(F.array(*[F.lit(m).cast("long") for m in masks]), lambda m: F.col("value").bitwiseXOR(m))
    index = index.select("item", F.col("n").alias("own_n"), "fingerprint", "block", F.explode(near).alias("value"))
    lookups = prints.select("c1", "c2", "own_n", "own_print", F.explode(entry(F.col("own_print"))).alias("e")).select("c1", "c2", "own_n", "own_print", "e.block", "e.value")
    distance = F.bit_count(F.col("own_print").bitwiseXOR(F.col("fingerprint")))
    candidates = lookups.join(index, ["own_n", "block", "value"]).where(distance <= radius).select("c1", "c2", "own_n", "item", distance.alias("distance")).distinct()

    pairs = candidates.join(prints.select("c1", "c2", "own_n", "own_places"), ["c1", "c2", "own_n"]).join(items.select("item", "weights", "whole", "foreign"), "item")
    shared = _mass(F.transform(F.array_intersect("own_places", F.map_keys("weights")), lambda h: F.try_element_at(F.col("weights"), h)))
    strange = F.size(F.filter("own_places", lambda h: ~F.array_contains(F.map_keys("weights"), h))) * F.col("foreign")
    pairs = pairs.withColumn("similarity", F.round(shared / (F.col("whole") + strange), 9)).where(F.col("similarity") >= similarity).select("c1", "c2", F.col("own_n").alias("n"), "item", "distance", "similarity")
    hits = windows.select("doc_id", "key", "start", "n", F.size("words").alias("n_words"), "c1", "c2").join(pairs, ["c1", "c2", "n"])
    best = F.max(F.struct("similarity", (-F.col("distance")).alias("near"), (-F.col("start")).alias("first"), "n_words")).alias("b")
    out = hits.groupBy("doc_id", "item").agg(best).join(names, "item")
    return out.select("doc_id", "item_id", (-F.col("b.first")).cast("long").alias("start"), F.col("b.n_words").cast("long").alias("n_words"), (-F.col("b.near")).cast("long").alias("distance"), F.col("b.similarity").alias("similarity"))


def decontaminate(docs: DataFrame, benchmark: DataFrame, **settings) -> DataFrame:
    """``docs`` without those that leak an item; rows and columns are otherwise as they were. A null doc_id goes if any null-id text leaks."""
    found = checkpointed(leaks(docs, benchmark, **settings).select(F.col("doc_id").alias("__leaks")).distinct())
    few = found.limit(BROADCAST_DOCS + 1).count() <= BROADCAST_DOCS
    return docs.join(F.broadcast(found) if few else found, docs["doc_id"].eqNullSafe(found["__leaks"]), "left_anti")
