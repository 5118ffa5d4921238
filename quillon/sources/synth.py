"""Generated transactions of known structure; randomness is a hash of row and item, the same in SQL."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def unit(seed: str, *parts: Column) -> Column:
    """A number in [0, 1) from the first eight hex digits of an MD5."""
    text = F.concat_ws("|", F.lit(seed), *(p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("double") / float(1 << 32)


def _kept(rows: DataFrame, flags: list[Column]) -> DataFrame:
    items = F.array(*(F.when(f, F.lit(f"i{k:02d}")) for k, f in enumerate(flags)))
    return rows.select(F.col("id").alias("tid"), F.filter(items, lambda x: x.isNotNull()).alias("items"))


def independent(spark: SparkSession, rows: int, items: int = 50, seed: str = "independent") -> DataFrame:
    """Items of frequencies spread over 0.2 to 0.8, independent."""
    return _kept(spark.range(rows), [unit(seed, F.col("id"), F.lit(k)) < 0.2 + 0.6 * k / max(items - 1, 1) for k in range(items)])


def chain(spark: SparkSession, rows: int, items: int = 50, seed: str = "chain") -> DataFrame:
    """Each item is equal to the one before it with a probability of 0.5 to 0.8, else the other way round."""
    coin = unit(seed, F.col("id"), F.lit("c")) < 0.5
    same = lambda k: unit(seed, F.col("id"), F.lit("k"), k) < 0.5 + 0.3 * k / max(items - 1, 1)
    grow = lambda bits, k: F.concat(bits, F.array(F.element_at(bits, -1) == same(k)))
    bits = F.aggregate(F.sequence(F.lit(1), F.lit(items - 1)), F.array(coin), grow)
    return _kept(spark.range(rows).withColumn("bits", bits), [F.element_at("bits", k + 1) for k in range(items)])


def mosaic(spark: SparkSession, rows: int, items: int = 50, seed: str = "mosaic") -> DataFrame:
    """Five planted sets of five items with frequencies 0.2 to 0.5, then one flip in a hundred."""
    flags = []
    for k in range(items):
        planted = unit(seed, F.col("id"), F.lit(f"s{k // 5}")) < 0.2 + 0.3 * (k // 5) / 4 if k < 25 else F.lit(False)
        flags.append(planted != (unit(seed, F.col("id"), F.lit(f"f{k}")) < 0.01))
    return _kept(spark.range(rows), flags)


def draws(spark: SparkSession, rows: int, items: int = 42, drawn: int = 7, seed: str = "draws") -> DataFrame:
    """A fair draw of 7 of 42 numbers a row: those with the smallest hashes."""
    order = F.array_sort(F.array(*(F.struct(unit(seed, F.col("id"), F.lit(k)).alias("u"), F.lit(f"i{k:02d}").alias("x")) for k in range(items))))
    return spark.range(rows).select(F.col("id").alias("tid"), F.array_sort(F.transform(F.slice(order, 1, drawn), lambda s: s["x"])).alias("items"))
