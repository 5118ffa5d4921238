"""N-gram Jaccard join by an R-tree over count vectors, in shards that lose no pair.

A document is the set of its distinct word shingles. Its count vector holds how many of them
hash into each of g groups, so two documents share at most the sum of the smaller counts. The
vectors are points of an R-tree whose boxes bound that sum for whole subtrees.

Points of random texts of one length lie close together, so that tree alone would visit most
pairs of equal length. The tables are therefore first cut into shards that no link crosses:
in one total order of all shingles, linked sets share one of their first |S| - ceil(0.8 |S|) + 1
(the prefix rule of set similarity joins). The order puts shingles that many documents hold last,
so that shared passages do not hold shards together. Documents that share a prefix shingle are a
candidate if their sizes and count vectors allow the similarity; the components of the candidates are
the shards, and each shard is joined through its own tree.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import bounded_batches, discard, map_batches, small, stored, text_slices
from .components import components, local_roots
from .textkernel import U, mix, shingle_sets

#: Shingles that a task holds before it counts the frequent ones.
COUNT_WINDOW = 1 << 20
#: Documents of a task that must hold a shingle, and documents in all, for it to go last in the order.
FREQUENT_IN_TASK, FREQUENT = 2, 12
#: Bits, 2 MB of them, in which those shingles are marked by hash. A rare one that shares a mark goes last with them:
#: any fixed rule makes an order, so that affects speed alone.
LATE_BITS = 1 << 24
#: Shingles and documents up to which one task joins a shard.
SHARD_SHINGLES, SHARD_DOCS = 1 << 20, 1024
LEAF = 16
#: Groups of the coarse count vectors. Sets of FINE or more also have a fine one, of some 8 to a group.
GROUPS, FINE = 64, 512
#: Documents before it in order of size with which a document of one prefix shingle is paired at once.
NEIGHBOURS = 32


class CountVectorTree:
    """R-tree over the count vectors of shingle sets, packed bottom up in order of size.

    Each node keeps, for its subtree, the largest count in every group and the smallest set size.
    The sum over groups of min(query count, largest count) bounds the overlap with any set below.
    """

    def __init__(self, sets: list[np.ndarray], groups: int | None = None):
        self.sizes = np.array([len(s) for s in sets], np.int64)
        middle = int(np.median(self.sizes)) if len(sets) else 1
        self.groups = groups or 1 << min(10, max(5, (middle // 2).bit_length()))
        self.points = np.stack([np.bincount((mix(s) % U(self.groups)).astype(np.int64), minlength=self.groups) for s in sets]).astype(np.int32) if sets else np.zeros((0, self.groups), np.int32)
        heavy = self.points[:, : self.groups // 2].sum(axis=1) if len(sets) else np.zeros(0)
        self.order = np.lexsort((heavy, self.sizes))
        boxes, least, self.levels = self.points[self.order], self.sizes[self.order], []
        while len(boxes) > LEAF:
            cuts = np.arange(0, len(boxes), LEAF)
            boxes, least = np.maximum.reduceat(boxes, cuts), np.minimum.reduceat(least, cuts)
            self.levels.append((boxes, least))

    def within(self, query: int, num: int, den: int) -> np.ndarray:
        """Members whose overlap with member `query` can reach num / den of the union."""
        q, size = self.points[query], int(self.sizes[query])

        def open_(boxes: np.ndarray, least: np.ndarray) -> np.ndarray:
            return (den + num) * np.minimum(boxes, q).sum(axis=1) >= num * (size + least)

        nodes = np.arange(len(self.levels[-1][0]) if self.levels else len(self.order))
        for boxes, least in reversed(self.levels):
            nodes = nodes[open_(boxes[nodes], least[nodes])]
            nodes = (nodes[:, None] * LEAF + np.arange(LEAF)).ravel()
            nodes = nodes[nodes < (len(self.order) if boxes is self.levels[0][0] else len(self.levels[self._below(boxes)][0]))]
        found = self.order[nodes]
        return found[open_(self.points[found], self.sizes[found])]

    def _below(self, boxes: np.ndarray) -> int:
        return next(k for k, (b, _) in enumerate(self.levels) if b is boxes) - 1


def count_vector(shingles: np.ndarray, groups: int = GROUPS) -> bytes | None:
    """Counts by group as 16-bit numbers; None, which bounds nothing, if one does not fit."""
    counts = np.bincount((mix(shingles) % U(groups)).astype(np.int64), minlength=groups)
    return None if counts.max() > 0xFFFF else counts.astype(np.uint16).tobytes()


def fine_vector(shingles: np.ndarray) -> bytes | None:
    """Count vector with a number of groups, a power of 2, that follows the set's size; None for small sets."""
    return count_vector(shingles, 1 << (len(shingles) // 8 - 1).bit_length()) if len(shingles) >= FINE else None


def shared_at_most(a: bytes, b: bytes) -> int:
    """Summed minima of two count vectors; the one with more groups is folded to the other's."""
    x, y = np.frombuffer(a, np.uint16), np.frombuffer(b, np.uint16)
    if len(x) > len(y):
        x, y = y, x
    return int(np.minimum(x, y.reshape(-1, len(x)).sum(axis=0)).sum())


def may_link(n: np.ndarray, m: np.ndarray, most: np.ndarray, num: int, den: int) -> np.ndarray:
    """Whether sets of n and m members that share `most` at most can have num / den of their union in common."""
    return (den + num) * np.minimum(most, np.minimum(n, m)) >= num * (n + m)


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Common members of two sorted arrays of distinct values."""
    if len(a) > len(b):
        a, b = b, a
    at = np.searchsorted(b, a)
    at[at == len(b)] = 0
    return int((b[at] == a).sum()) if len(b) else 0


def tree_links(sets: list[np.ndarray], num: int = 80, den: int = 100, side: np.ndarray | None = None) -> Iterator[tuple[int, int]]:
    """Links (i, j) that join the sets of one component, fewer than there are sets.

    Candidates come from the tree; those already in one component are passed over, the others are
    verified on their whole sets: linked if den * |a & b| >= num * |a | b|. With `side`, only
    pairs from different sides count.
    """
    tree, comp = CountVectorTree(sets), np.arange(len(sets))
    for i in np.argsort(tree.sizes, kind="stable").tolist():
        near = tree.within(i, num, den)
        near = near[(comp[near] != comp[i]) & (side is None or side[near] != side[i])]
        while len(near):
            j = int(near[0])
            common = overlap(sets[i], sets[j])
            if den * common >= num * (tree.sizes[i] + tree.sizes[j] - common):
                yield i, j
                comp[comp == comp[j]] = comp[i]
                near = near[comp[near] != comp[i]]
            else:
                near = near[1:]


def _signature(shingles: np.ndarray) -> bytes:
    return hashlib.blake2b(shingles.tobytes(), digest_size=16).digest()


def _frequent(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that FREQUENT_IN_TASK of the sets hold, and in how many."""
    if not sets:
        return np.zeros(0, U), np.zeros(0, np.int64)
    values = np.concatenate(sets)
    sets.clear()
    values.sort()
    often = np.flatnonzero(values[FREQUENT_IN_TASK - 1 :] == values[: len(values) - FREQUENT_IN_TASK + 1])
    found = np.unique(values[often])
    return found, np.searchsorted(values, found, side="right") - np.searchsorted(values, found, side="left")


def _profile(width: int):
    """Set size and signature of each document, and the shingles frequent in this task."""
    schema = pa.schema([("id", pa.int64()), ("n", pa.int64()), ("sig", pa.binary()), ("vec", pa.binary()), ("fine", pa.binary()), ("shingle", pa.int64()), ("docs", pa.int64())])

    def frequent(sets: list[np.ndarray]) -> pa.RecordBatch:
        values, counts = _frequent(sets)
        none = pa.nulls(len(values))
        return pa.RecordBatch.from_arrays([none.cast(pa.int64()), none.cast(pa.int64()), *[none.cast(pa.binary())] * 3, pa.array(values.view(np.int64)), pa.array(counts)], schema=schema)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        window, held, seen = [], 0, set()
        for rows, data, at in text_slices(batches):
            sets = shingle_sets(data, at, width)
            sigs = [_signature(s) if len(s) else None for s in sets]
            none = pa.nulls(len(sets), pa.int64())
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array([len(s) for s in sets], pa.int64()), pa.array(sigs, pa.binary()), pa.array([count_vector(x) for x in sets], pa.binary()), pa.array([fine_vector(x) for x in sets], pa.binary()), none, none], schema=schema)
            for s, sig in zip(sets, sigs, strict=True):
                if sig and sig not in seen:
                    seen.add(sig)
                    window.append(s)
                    held += len(s)
            if held >= COUNT_WINDOW:
                yield frequent(window)
                window, held, seen = [], 0, set()
        yield frequent(window)

    return run


def prefix_length(n: int, num: int, den: int) -> int:
    """How many first shingles of a set of n must hold one that a linked set has among its first."""
    return n - -(-num * n // den) + 1


def _late(often: DataFrame) -> np.ndarray:
    """Marks of the frequent shingles; LATE_BITS / 64 numbers at most come to the driver, whatever their count."""
    spot = often.select(F.expr(f"pmod(shiftrightunsigned(shingle, 20), {LATE_BITS}L)").alias("spot"))
    words = spot.groupBy(F.shiftright("spot", 6).alias("word")).agg(F.expr("bit_or(shiftleft(1L, cast(spot % 64 as int)))").alias("bits")).toPandas()
    out = np.zeros(LATE_BITS // 64, U)
    out[words["word"].to_numpy(np.int64)] = words["bits"].to_numpy(np.int64).view(U)
    return out


def _prefixes(width: int, last: "object", num: int, den: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        late = last.value
        for rows, data, at in text_slices(batches):
            keys, sigs = [], []
            for s in shingle_sets(data, at, width):
                sigs.append(_signature(s) if len(s) else None)
                n = prefix_length(len(s), num, den) if len(s) else 0
                if n:
                    spot = (s >> U(20)) & U(LATE_BITS - 1)
                    often = (late[spot >> U(6)] >> (spot & U(63))) & U(1) == 1
                    s = np.concatenate((s[~often][:n], s[often][:n]))
                keys.append(s[:n].view(np.int64))
            lengths = np.cumsum([0, *map(len, keys)])
            values = np.concatenate(keys) if keys else np.zeros(0, np.int64)
            yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(sigs, pa.binary()), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(values))], names=["id", "sig", "keys"])

    return run


def _bounded(num: int, den: int):
    """Of pairs (a, b, n, m, va, vb) those whose sizes and count vectors allow the similarity."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            n, m = rows.column(2).to_numpy(), rows.column(3).to_numpy()
            most = np.minimum(n, m)
            for k, (a, b) in enumerate(zip(rows.column(4).to_pylist(), rows.column(5).to_pylist(), strict=True)):
                if a is not None and b is not None:
                    most[k] = shared_at_most(a, b)
            yield pa.RecordBatch.from_arrays(rows.columns[:4], names=["a", "b", "n", "m"]).filter(pa.array(may_link(n, m, most, num, den)))

    return run


def _bound_task(num: int, den: int):
    """Links between the documents of one task whose bounds allow the similarity; enough to join their components."""

    def run(table: pa.Table) -> pa.Table:
        ids, n = table.column("id").to_numpy(), table.column("n").to_numpy()
        vecs = np.stack([np.full(GROUPS, 0xFFFF, np.uint16) if v is None else np.frombuffer(v, np.uint16) for v in table.column("vec").to_pylist()]).astype(np.int64)
        i, j = [], []
        for k in range(1, len(ids)):
            hit = np.flatnonzero(may_link(n[:k], n[k], np.minimum(vecs[:k], vecs[k]).sum(axis=1), num, den))
            i.append(np.full(len(hit), k))
            j.append(hit)
        root = local_roots(len(ids), np.concatenate([np.zeros(0, np.int64), *i]), np.concatenate([np.zeros(0, np.int64), *j]))
        some = np.flatnonzero(root != np.arange(len(ids)))
        return pa.table({"a": ids[some], "b": ids[root[some]]})

    return run


def _candidates(keyed: DataFrame, classes: DataFrame, num: int, den: int) -> DataFrame:
    """(id, cluster): documents that share prefix shingles, by component of the pairs that their bounds allow.

    Within a shingle's documents, in order of size, each is paired with the NEIGHBOURS before it; linked
    sets are near in that order unless many others lie between. Shingles where that happens are gone
    through again by tiles of documents and their vectors, if they join more than one component.
    """
    by_size = Window.partitionBy("key").orderBy("n", "id").rowsBetween(-NEIGHBOURS, -1)
    before = keyed.withColumn("before", F.collect_list(F.struct("id", "n", "pos")).over(by_size)).where(F.size("before") > 0)
    reach = lambda p: den * p["n"] >= num * F.col("n")
    # if this is the first common shingle, what stands before it in either set is not shared
    first = lambda p: (den + num) * F.least(p["n"] - p["pos"], F.col("n") - F.col("pos")) >= num * (p["n"] + F.col("n"))
    before = before.select("key", "id", F.transform(F.filter("before", lambda p: reach(p) & first(p)), lambda p: p["id"]).alias("near"), ((F.size("before") == NEIGHBOURS) & reach(F.element_at("before", 1))).alias("more"))
    before = stored(before.where((F.size("near") > 0) | F.col("more")), "before")
    pairs = before.select("id", "near").distinct().select(F.col("id").alias("b"), F.explode("near").alias("a")).where("a != b").distinct()
    of = lambda k, n, vec, v: classes.select(F.col("vertex").alias(k), F.col("n").alias(n), F.col(vec).alias(v))
    kept = "a long, b long, n long, m long"
    pairs = pairs.join(of("a", "n", "vec", "va"), "a").join(of("b", "m", "vec", "vb"), "b").select("a", "b", "n", "m", "va", "vb")
    pairs = stored(map_batches(pairs, _bounded(num, den), kept), "pairs")
    large = pairs.where((F.col("n") >= FINE) & (F.col("m") >= FINE))
    large = map_batches(large.join(of("a", "n", "fine", "va"), ["a", "n"]).join(of("b", "m", "fine", "vb"), ["b", "m"]).select("a", "b", "n", "m", "va", "vb"), _bounded(num, den), kept)
    edges = stored(pairs.where((F.col("n") < FINE) | (F.col("m") < FINE)).union(large).select("a", "b"), "edges")
    found = components(edges)
    crowded = stored(before.where("more").select("key").distinct(), "crowded")
    if crowded.isEmpty():
        return found
    members = keyed.join(small(crowded), "key", "left_semi").join(found, "id", "left").withColumn("component", F.coalesce("component", "id"))
    split = stored(members.groupBy("key").agg(F.min("component").alias("x"), F.max("component").alias("y")).where("x != y").select("key"), "split")
    if split.isEmpty():
        return found
    rest = stored(keyed.join(small(split), "key", "left_semi").select("id", F.col("key").alias("cluster"), "n"), "rest")
    tiles = stored(_shards(rest), "bound_tiles").join(classes.select(F.col("vertex").alias("id"), "n", "vec"), "id")
    more = tiles.groupBy("cluster", "lo", "hi").applyInArrow(_bound_task(num, den), "a long, b long")
    return components(edges.union(more))


def _shard_task(width: int, num: int, den: int):
    def run(table: pa.Table) -> pa.Table:
        sets: list[np.ndarray] = []
        for batch in table.select(["text"]).to_batches():
            for _, data, at in text_slices([batch]):
                sets += shingle_sets(data, at, width)
        # rows with one id may have different texts; those that are not the class's own go
        own = [k for k, (s, sig) in enumerate(zip(sets, table.column("sig").to_pylist(), strict=True)) if _signature(s) == sig]
        sets, ids, tile = [sets[k] for k in own], table.column("vertex").to_numpy()[own], table.column("tile").to_numpy()[own]
        side = None if table.column("lo")[0].as_py() == table.column("hi")[0].as_py() else tile
        links = list(tree_links(sets, num, den, side)) if sets else []
        return pa.table({"a": pa.array([ids[i] for i, _ in links], pa.int64()), "b": pa.array([ids[j] for _, j in links], pa.int64())})

    return run


def _shards(clusters: DataFrame) -> DataFrame:
    """(id, cluster, lo, hi, tile): which tasks a document takes part in.

    A shard within SHARD_SHINGLES and SHARD_DOCS is one task. A larger one is cut by size into bands
    such that linked sets lie in one band or in neighbours, and each band by hash into tiles; a task
    takes a pair of tiles.
    """
    total = clusters.groupBy("cluster").agg(F.count("*").alias("docs"), F.sum("n").alias("shingles"))
    large = stored(total.where((F.col("docs") > SHARD_DOCS) | (F.col("shingles") > SHARD_SHINGLES)).select("cluster"), "large")
    few = small(large)
    whole = clusters.join(few, "cluster", "left_anti").select("id", "cluster", F.lit("").alias("lo"), F.lit("").alias("hi"), F.lit("").alias("tile"))
    if large.isEmpty():
        return whole
    banded = clusters.join(few, "cluster", "left_semi").withColumn("band", F.floor(F.log2("n") * 3).cast("int"))  # 2^(1/3) > 1 / 0.8
    counts = banded.groupBy("cluster", "band").agg(F.count("*").alias("docs"), F.sum("n").alias("shingles"))
    tiles = stored(counts.select("cluster", "band", F.ceil(F.greatest(F.col("docs") / (SHARD_DOCS // 2), F.col("shingles") / (SHARD_SHINGLES // 2))).cast("int").alias("tiles")), "tiles")
    near = lambda d: small(tiles.select("cluster", (F.col("band") - d).alias("band"), F.col("tiles").alias({0: "own", 1: "up", -1: "down"}[d])))
    dealt = banded.join(near(0), ["cluster", "band"]).join(near(1), ["cluster", "band"], "left").join(near(-1), ["cluster", "band"], "left")
    dealt = dealt.withColumn("t", F.pmod(F.xxhash64("id", F.lit(11)), "own"))
    name = lambda band, t: F.format_string("%05d-%09d", band, t.cast("long"))
    every = lambda n: F.when(F.col(n) > 0, F.sequence(F.lit(0), F.col(n) - 1)).otherwise(F.array().cast("array<int>"))
    # the function has one parameter: Spark gives a second one, even with a default, the place in the array
    tiles_of = lambda n, d: F.transform(every(n), lambda x: F.struct((F.col("band") + d).alias("band"), x.cast("long").alias("t")))
    partners = F.concat(tiles_of("own", 0), tiles_of("up", 1), tiles_of("down", -1))
    dealt = dealt.withColumn("w", F.explode(partners)).withColumn("tile", name(F.col("band"), F.col("t"))).withColumn("other", name(F.col("w.band"), F.col("w.t")))
    return whole.union(dealt.select("id", "cluster", F.least("tile", "other").alias("lo"), F.greatest("tile", "other").alias("hi"), "tile"))


def _classes(each: DataFrame) -> DataFrame:
    """(sig, rep, n, vec, fine, vertex): one row for each distinct set, with its smallest id.

    The vertex is that id; where several sets have it, as ids repeat, or there is none, it is a negative number
    that the set gives.
    """
    spark = each.sparkSession
    sets = stored(each.where("n > 0").groupBy("sig").agg(F.min("id").alias("rep"), F.max("n").alias("n"), F.max("vec").alias("vec"), F.max("fine").alias("fine")), "sets")
    shared = stored(sets.where("rep is not null").groupBy("rep").agg(F.count("*").alias("sets")).where("sets > 1").select("rep", F.lit(True).alias("shared")), "shared")
    own = -F.pmod(F.xxhash64("sig"), F.lit(1 << 62)) - 1
    named = sets.join(small(shared), "rep", "left") if not shared.isEmpty() else sets.withColumn("shared", F.lit(None).cast("boolean"))
    out = stored(named.withColumn("vertex", F.when(F.col("rep").isNull() | F.coalesce("shared", F.lit(False)), own).otherwise(F.col("rep"))).drop("shared"), "classes")
    discard(spark, sets, shared)
    return out


def _without_repeats(docs: DataFrame, each: DataFrame) -> DataFrame:
    """`docs` (id, text) with one row of those that repeat both."""
    repeated = stored(each.where("n > 0").groupBy("id", "sig").count().where("count > 1").select(F.col("id").alias("again")).distinct(), "repeated")
    if repeated.isEmpty():
        return docs
    same, few = docs["id"].eqNullSafe(repeated["again"]), small(repeated)
    return docs.join(few, same, "left_anti").union(docs.join(few, same, "left_semi").dropDuplicates(["id", "text"]))


def jaccard_groups(docs: DataFrame, num: int = 80, den: int = 100, width: int = 5, key: str = "doc_id", text: str = "text") -> tuple[DataFrame, DataFrame]:
    """(id, n, sig) of each row, and (sig, rep, n, group, low) of each distinct set.

    `rep` is the smallest id of a set, `group` tells the linked sets (null: linked with none), `low` is the
    smallest id of the group, or of the set without one. See `jaccard_components` for what links and for odd rows.
    """
    if num * 5 < den * 4:
        raise ValueError("the size bands need a similarity of 0.8 or more")
    docs = docs.select(F.col(key).cast("long").alias("id"), F.col(text).alias("text"))
    spark = docs.sparkSession
    bounded_batches(spark)
    profile = stored(map_batches(docs, _profile(width), "id long, n long, sig binary, vec binary, fine binary, shingle long, docs long"), "profile")
    each = profile.where("shingle is null").select("id", "n", "sig", "vec", "fine")
    often = profile.where("shingle is not null").groupBy("shingle").agg(F.sum("docs").alias("docs")).where(F.col("docs") >= FREQUENT)
    last = spark.sparkContext.broadcast(_late(often))
    classes = _classes(each)
    docs = _without_repeats(docs, each)
    keys = stored(map_batches(docs, _prefixes(width, last, num, den), "id long, sig binary, keys array<long>"), "keys")
    last.unpersist()
    keyed = keys.join(classes.select(F.col("rep").alias("id"), "sig", "n", "vertex").where("id is not null"), ["id", "sig"])
    nameless = classes.where("rep is null")
    if not nameless.isEmpty():  # sets of rows without an id: any one of them stands for the set
        some = keys.where("id is null").groupBy("sig").agg(F.any_value("keys").alias("keys"))
        keyed = keyed.select("vertex", "n", "keys").union(some.join(nameless, "sig").select("vertex", "n", "keys"))
    keyed = keyed.select(F.col("vertex").alias("id"), "n", F.posexplode("keys").alias("pos", "key"))
    clusters = _candidates(keyed, classes, num, den).withColumnRenamed("component", "cluster")
    clusters = stored(clusters.join(classes.select(F.col("vertex").alias("id"), "n"), "id"), "clusters")
    shards = stored(_shards(clusters).join(classes.select(F.col("vertex").alias("id"), "rep", "sig"), "id").withColumnRenamed("id", "vertex"), "shards")
    discard(spark, keys, clusters)
    texts = docs.join(small(shards), docs["id"].eqNullSafe(shards["rep"])).drop("id", "rep")
    links = texts.groupBy("cluster", "lo", "hi").applyInArrow(_shard_task(width, num, den), "a long, b long")
    comps = components(links)
    discard(spark, shards)
    members = stored(classes.join(comps.select(F.col("id").alias("vertex"), F.col("component").alias("group")), "vertex", "left").select("sig", "rep", "n", "group"), "members")
    discard(spark, classes)
    low = members.where("group is not null").groupBy("group").agg(F.min("rep").alias("lowest"))
    named = members.join(low, "group", "left").select("sig", "rep", "n", "group", F.coalesce("lowest", "rep").alias("low"))
    return each.select("id", "n", "sig"), stored(named, "groups")


def jaccard_components(docs: DataFrame, num: int = 80, den: int = 100, width: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per document: key, n_shingles, component_id.

    Documents link if den * intersection >= num * union of their shingle sets (num / den >= 0.8 with
    the bands used). Null, empty and wordless texts have the empty set and link with nothing; texts of
    fewer than `width` words are one shingle. Repeated rows give repeated rows; rows with one id and different
    texts are documents of their own. A null id is never a component's smallest one, unless all are null.
    Documents with equal sets are joined as one. An empty table gives an empty result; other columns, whatever
    their names, are ignored.
    """
    each, sets = jaccard_groups(docs, num, den, width, key, text)
    low = sets.select("sig", "low")
    return each.join(low, "sig", "left").select(F.col("id").alias(key), F.col("n").alias("n_shingles"), F.coalesce("low", "id").alias("component_id"))


def _with_set(docs: DataFrame, width: int, text: str, names: tuple[str, str]) -> DataFrame:
    """All columns, with the size and the signature of each row's set."""
    schema = T.StructType([*docs.schema.fields, T.StructField(names[0], T.LongType()), T.StructField(names[1], T.BinaryType())])

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, data, at in text_slices(batches, text):
            sets = shingle_sets(data, at, width)
            new = [pa.array([len(s) for s in sets], pa.int64()), pa.array([_signature(s) if len(s) else None for s in sets], pa.binary())]
            yield pa.RecordBatch.from_arrays([*rows.columns, *new], names=[*rows.schema.names, *names])

    return map_batches(docs, run, schema)


def one_of_each_group(docs: DataFrame, num: int = 80, den: int = 100, width: int = 5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The rows of `docs` without near copies: of each group of linked texts one row, that with the smallest id.

    Rows without words link with nothing and all stay. Rows with one id are held apart by their sets, so
    different texts under one id both stay; of rows with equal sets one stays. Null ids come after all others. Columns
    come back as they were, whatever their names, but for two that hold a set meanwhile (`__n`, `__sig`).
    """
    each, sets = jaccard_groups(docs, num, den, width, key, text)
    spark = docs.sparkSession
    alone = F.coalesce(F.col("group"), F.xxhash64("sig"))
    first = sets.groupBy(F.col("group").isNull().alias("single"), alone.alias("of"), F.when(F.col("group").isNull(), F.col("sig")).alias("own"))
    first = first.agg(F.min(F.struct(F.col("rep").isNull(), "rep", "sig")).alias("f"))
    kept = stored(first.select(F.col("f.rep").alias("kept"), F.col("f.sig").alias("kept_sig")), "kept")
    counts = each.groupBy("id").agg(F.count("*").alias("rows"))
    unclear = stored(counts.where("rows > 1 or id is null").select(F.col("id").alias("unclear")), "unclear")
    ids = stored(kept.select(F.col("kept").alias("stays")).union(each.where("n = 0").select("id")).where("stays is not null").join(unclear, F.col("stays") == F.col("unclear"), "left_anti").distinct(), "stays")
    out = docs.join(small(ids), docs[key].cast("long") == ids["stays"], "left_semi")
    if unclear.isEmpty():
        return out
    rows = _with_set(docs.join(small(unclear), docs[key].cast("long").eqNullSafe(unclear["unclear"]), "left_semi"), width, text, ("__n", "__sig"))
    rows = stored(rows, "unclear_rows")
    named = rows.where("`__n` > 0")
    named = named.join(small(kept), named[key].cast("long").eqNullSafe(kept["kept"]) & (named["__sig"] == kept["kept_sig"]), "left_semi").dropDuplicates([key, "__sig"])
    return out.unionByName(rows.where("`__n` = 0").union(named).drop("__n", "__sig"))
