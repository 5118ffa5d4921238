"""Mixing sources to target weights, with DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import small, stored

#: Words of a block, slots of an output shard, rows that a window over documents orders, about.
BLOCK_WORDS, SHARD_SLOTS, CHUNK_ROWS = 64, 4096, 1024
#: Output shards there are at least, if there are as many slots, and shards whose draws are rotations of each other.
LEAST_SHARDS, ROTATED = 256, 256
#: Shards of one window of running sums, and slots that a task lays out, about.
BAND_SHARDS, TASK_SLOTS = 1024, 1 << 18
#: Cells into which the draw's unit interval is cut to find a slot's source by an equi-join.
CELLS = 4096
#: Rounds of the permutation of block indices.
ROUNDS = 4


def word_count(text: str = "text") -> Column:
    """Number of runs of characters other than 0x20 and 0x09-0x0D; null: 0."""
    return F.coalesce(F.length(F.regexp_replace(text, r"[^\x20\x09-\x0D]+", "w")) - F.length(F.regexp_replace(text, r"[^\x20\x09-\x0D]+", "")), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """(source, source_size) to (source, source_size, target).

    In order of code points, null last, sources weigh `weights` over and over; they share `share` times
    all sizes by weight, and none gets over `most` times its size: what is over goes to the others by
    weight, again and again. In order of size by weight the capped sources come first, so one cut tells
    them: a source is capped if the level of those after the ones before it reaches its cap. Sources with
    no words get 0. Windows here are over sources, not documents.
    """
    weigh = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.col("at") - 1, F.lit(len(weights))) + 1).cast("int"))
    # utf8 order of strings is the order of their code points
    rows = sizes.withColumn("at", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))).withColumn("weight", weigh.cast("double"))
    rows = rows.withColumn("cap", most * F.col("source_size")).withColumn("ratio", F.col("cap") / F.col("weight"))
    before = Window.orderBy("ratio", "at").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("used", F.coalesce(F.sum("cap").over(before), F.lit(0.0))).withColumn("gone", F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    every = Window.partitionBy()
    rows = rows.withColumn("all", share * F.sum("source_size").over(every)).withColumn("heavy", F.sum("weight").over(every))
    rows = rows.withColumn("level", (F.col("all") - F.col("used")) / (F.col("heavy") - F.col("gone"))).withColumn("capped", F.col("ratio") <= F.col("level"))
    free = F.min(F.when(~F.col("capped"), F.col("ratio"))).over(every)
    level = F.max(F.when(F.col("ratio") == free, F.col("level"))).over(every)
    return rows.withColumn("final", F.coalesce(level, F.lit(0.0))).select("source", "source_size", F.when(F.col("capped"), F.col("cap")).otherwise(F.col("final") * F.col("weight")).alias("target"))


def packed(docs: DataFrame, rows: int) -> DataFrame:
    """Adds `start`: the place of a document's first word in its source's words.

    Documents go to chunks by hash; a chunk's start is a sum over chunks, a document's a sum within its
    chunk, so no window holds a whole source.
    """
    chunks = max(16, -(-rows // CHUNK_ROWS))
    dealt = docs.withColumn("chunk", F.pmod(F.xxhash64("doc_id", "mark", F.lit(3)), F.lit(chunks)))
    sums = dealt.groupBy("source", "chunk").agg(F.sum("size").alias("words"))
    bases = running(sums, "chunk", "words", CHUNK_ROWS).select(F.col("source").alias("s"), F.col("chunk").alias("c"), F.col("ahead").alias("base"))
    inside = Window.partitionBy("source", "chunk").orderBy("doc_id", "size", "mark").rowsBetween(Window.unboundedPreceding, -1)
    dealt = dealt.withColumn("within", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    joined = dealt.join(bases, dealt["source"].eqNullSafe(bases["s"]) & (dealt["chunk"] == bases["c"]))
    return joined.withColumn("start", F.col("base") + F.col("within")).drop("s", "c", "base", "within", "chunk")


def running(rows: DataFrame, place: str, value: str, band: int) -> DataFrame:
    """Adds `ahead`: the sum of `value` over the rows of the same source at lower places; two levels, so that
    a window holds `band` places of a source, or its bands.
    """
    rows = rows.withColumn("band", F.floor(F.col(place) / band))
    bands = rows.groupBy("source", "band").agg(F.sum(value).alias("__sum"))
    before = lambda keys, order: Window.partitionBy(*keys).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    bands = bands.select(F.col("source").alias("__s"), F.col("band").alias("__b"), F.coalesce(F.sum("__sum").over(before(["source"], "band")), F.lit(0)).alias("__base"))
    inner = rows.withColumn("__in", F.coalesce(F.sum(value).over(before(["source", "band"], place)), F.lit(0)))
    joined = inner.join(bands, inner["source"].eqNullSafe(bands["__s"]) & (inner["band"] == bands["__b"]))
    return joined.withColumn("ahead", F.col("__base") + F.col("__in")).drop("__s", "__b", "__base", "__in", "band")


def uniform(seed: int, *columns) -> Column:
    """A number in [0, 1) that the columns determine."""
    return F.pmod(F.xxhash64(*columns, F.lit(seed)), F.lit(1 << 40)) / float(1 << 40)


def drawn_slots(targets: DataFrame, block_words: int = BLOCK_WORDS, shard_slots: int = SHARD_SLOTS, seed: int = 5) -> DataFrame:
    """(shard, source, blocks, n, ahead): how many slots of a shard are a source's, and how many of its slots
    are in the shards before.

    A source's share of the slots is its target in blocks of its mean size. Each slot of a shard draws a
    uniform point of the unit interval and belongs to the source whose share covers it; the slots of a shard
    draw independently, so its counts are multinomial. Shards of one group draw the same points, each turned
    by its own multiple of one part of the interval: a turned uniform point is uniform, so every shard's
    counts stay multinomial, but the group's counts together come within rounding of their expectation,
    which keeps the sources near their targets.
    """
    spark = targets.sparkSession
    live = targets.where(F.col("source_size") > 0).withColumn("blocks", F.ceil(F.col("source_size") / block_words)).withColumn("slots", F.col("target") * F.col("blocks") / F.col("source_size"))
    up_to = Window.orderBy(F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, 0)
    shares = live.withColumn("high", F.sum("slots").over(up_to)).withColumn("total", F.sum("slots").over(Window.partitionBy()))
    shares = stored(shares.select("source", "blocks", "total", ((F.col("high") - F.col("slots")) / F.col("total")).alias("low"), F.when(F.col("high") == F.col("total"), 1.0).otherwise(F.col("high") / F.col("total")).alias("high")), "shares")
    total = round(shares.agg(F.max("total")).first()[0] or 0)
    cells = shares.withColumn("cell", F.explode(F.sequence(F.floor(F.col("low") * CELLS), F.least(F.floor(F.col("high") * CELLS), F.lit(CELLS - 1)))))
    shards = max(-(-total // shard_slots), min(LEAST_SHARDS, total), 1)
    own = max(-(-total // shards), 1)  # slots of a shard
    parts = max(spark.sparkContext.defaultParallelism, -(-total // (1 << 22)))
    slots = spark.range(0, total, 1, parts).select(F.floor(F.col("id") / own).alias("shard"), (F.col("id") % own).alias("slot"))
    group = F.floor(F.col("shard") / ROTATED)
    turn = (F.col("shard") % ROTATED) / F.least(F.lit(ROTATED), F.lit(-(-total // own)) - group * ROTATED)
    point = uniform(seed, group, "slot") + turn
    slots = slots.withColumn("u", point - F.floor(point)).withColumn("cell", F.floor(F.col("u") * CELLS))
    drawn = slots.join(small(cells), "cell").where((F.col("u") >= F.col("low")) & (F.col("u") < F.col("high")))
    counts = stored(drawn.groupBy("shard", "source", "blocks").agg(F.count("*").alias("n")), "counts")
    return running(counts, "shard", "n", BAND_SHARDS).repartition(max(1, -(-total // TASK_SLOTS)), "source", "shard")


def permuted(t: Column, blocks: Column, *key) -> Column:
    """The place of index `t` in a keyed pseudorandom permutation of 0 .. blocks - 1.

    A Feistel network over pairs (l, r) below a and b, the least a x b grid with at least `blocks` points and
    a = ceil(sqrt(blocks)); while it leads out of the range it is applied again, which happens to fewer than
    one index in sqrt(blocks), and at most as often as the grid has points too many.
    """
    a = F.ceil(F.sqrt(blocks.cast("double")))
    b = F.ceil(blocks / a)

    def once(x: Column) -> Column:
        left, right = F.floor(x / b), x % b
        for k in range(ROUNDS):
            if k % 2:
                right = (right + F.pmod(F.xxhash64(left, F.lit(k), *key), b)) % b
            else:
                left = (left + F.pmod(F.xxhash64(right, F.lit(k), *key), a)) % a
        return left * b + right

    first = once(t)
    walked = F.aggregate(F.sequence(F.lit(1).cast("long"), a * b - blocks), first, lambda x, _: F.when(x >= blocks, once(x)).otherwise(x))
    return F.when(first >= blocks, walked).otherwise(first)


def slot_blocks(slots: DataFrame, most: int = 2, seed: int = 9) -> DataFrame:
    """(shard, source, slot, block, pass): each slot's block, through the source's permutation of block indices.

    Pass p of a source goes through all its blocks once, in the order of a permutation keyed by source and
    pass. Slots after pass `most` stay empty.
    """
    rows = slots.withColumn("slot", F.explode(F.sequence(F.col("ahead"), F.col("ahead") + F.col("n") - 1))).where(F.col("slot") < most * F.col("blocks"))
    rows = rows.withColumn("pass", F.floor(F.col("slot") / F.col("blocks"))).withColumn("t", F.col("slot") % F.col("blocks"))
    return rows.select("shard", "source", "slot", permuted(F.col("t"), F.col("blocks"), "source", "pass", F.lit(seed)).alias("block"), "pass")


def _mixture(docs: DataFrame, weights: tuple[int, ...], share: float, most: int, block_words: int, key: str, text: str, source: str) -> DataFrame:
    """As `mixture`, with `mark`: a hash of id, source and text, which tells rows of one id apart."""
    sized = stored(docs.select(F.col(key).alias("doc_id"), F.col(source).alias("source"), word_count(text).alias("size"), _mark(key, source, text).alias("mark")), "sizes")
    rows = sized.count()
    targets = stored(source_targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most), "targets")
    places = stored(packed(sized, rows), "places")
    uses = slot_blocks(drawn_slots(targets, block_words), most).groupBy("source", "block").agg(F.count("*").alias("uses")).select(F.col("source").alias("s"), F.col("block").alias("b"), "uses")
    last = F.floor((F.col("start") + F.col("size") - 1) / block_words)
    parts = places.where("size > 0").withColumn("block", F.explode(F.sequence(F.floor(F.col("start") / block_words), last)))
    words = F.least(F.col("start") + F.col("size"), (F.col("block") + 1) * block_words) - F.greatest(F.col("start"), F.col("block") * block_words)
    # the planner takes rows made by explode to be as few as those they come from, and would broadcast all blocks
    parts = parts.join(uses.hint("merge"), parts["source"].eqNullSafe(uses["s"]) & (parts["block"] == uses["b"]), "left")
    taken = parts.groupBy("doc_id", "source", "size", "mark", "start").agg(F.sum(words * F.coalesce("uses", F.lit(0))).cast("long").alias("taken")).drop("start")
    every = taken.union(places.where("size = 0").select("doc_id", "source", "size", "mark", F.lit(0).cast("long").alias("taken")))
    named = targets.select(F.col("source").alias("s"), "source_size", "target")
    return every.join(small(named, 10_000), every["source"].eqNullSafe(F.col("s"))).drop("s")


def _mark(key: str, source: str, text: str) -> Column:
    return F.xxhash64(F.col(key), F.col(source), F.col(text))


def mixture(docs: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: int = 2, block_words: int = BLOCK_WORDS, key: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """Per document: doc_id, source, size, source_size, target, taken.

    Every source's words, document after document, are packed into blocks of `block_words`; slots are drawn
    for sources, mapped to blocks and joined by block index; `taken` counts the words of a document in the
    blocks taken, repeats counted. Each pass takes a block once at most, so no document exceeds `most` times
    its size. The result depends on the rows alone. Null texts have size 0; null is a source; a null id is an
    id like others; rows with equal ids are documents of their own. Empty tables give empty results; other
    columns, whatever their names, are ignored.
    """
    return _mixture(docs, weights, share, most, block_words, key, text, source).drop("mark")


def mixed_documents(docs: DataFrame, seed: int = 13, key: str = "doc_id", text: str = "text", source: str = "source") -> DataFrame:
    """The rows of `docs`, each as many times as the mixture takes it: taken / size, rounded down or up by a draw.

    Documents without words are not taken. Rows that repeat id, source and text share what they are taken
    together. Null ids count as ids. All columns come back as they were, whatever their names.
    """
    mix = _mixture(docs, (3, 1, 2), 1.5, 2, BLOCK_WORDS, key, text, source).where("size > 0").groupBy("mark").agg((F.sum("taken") / F.sum("size")).alias("times"))
    times = stored(mix.select("mark", F.floor(F.col("times") + uniform(seed, "mark")).cast("int").alias("copies")).where("copies > 0"), "times")
    out = docs.select(F.struct("*").alias("row"), _mark(key, source, text).alias("mark")).join(small(times), "mark")
    return out.select("row", F.explode(F.sequence(F.lit(1), "copies"))).select("row.*")
