"""Connected components of link tables, and joins that no hot key holds up."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from traincube.llm.scratch import discard, materialize

#: A key is hot if it has more rows than both this and a ten-thousandth of all rows.
HOT_ROWS = 2048
HOT_SHARE = 10_000


def meet(rows: DataFrame, per_key: DataFrame, key: str, spread: str, total: int) -> DataFrame:
    """Inner join of ``total`` rows with one row for each key, whose column n counts the key's rows.

    A hot key's row is copied and its rows are dealt over the copies by the column
    ``spread``, so that no task gets all of them. At most HOT_SHARE keys can be hot, by
    the definition of hot, so the list of them is small enough to broadcast.
    """
    if total <= HOT_ROWS:
        return rows.join(per_key.drop("n"), key)
    most = max(HOT_ROWS, total // HOT_SHARE)
    deals = F.ceil(F.col("n") / most).cast("int")
    hot = per_key.where(F.col("n") > most).select(F.col(key).alias("_hot"), deals.alias("_deals"))
    dealt = rows.join(F.broadcast(hot), F.col(key) == F.col("_hot"), "left").withColumn("_deal", F.pmod(F.xxhash64(spread), F.coalesce("_deals", F.lit(1))).cast("int"))
    copies = per_key.withColumn("_deal", F.explode(F.sequence(F.lit(0), deals - 1))).drop("n")
    # Large tables on both sides; else a broadcast of the second would fill the driver.
    return dealt.drop("_hot", "_deals").join(copies.hint("merge"), [key, "_deal"]).drop("_deal")


def _least(pairs: DataFrame, total: int) -> DataFrame:
    """Links (a, b) with the smallest b, or a itself, of each a."""
    return meet(pairs, pairs.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"), F.count("*").alias("n")), "a", "b", total)


def _large_star(links: DataFrame) -> DataFrame:
    both = links.union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    return _least(both, 2 * links.count()).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(links: DataFrame) -> DataFrame:
    down = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    met = _least(down, links.count())
    return met.select(F.col("b").alias("a"), F.col("m").alias("b")).union(met.select("a", F.col("m").alias("b"))).where("a <> b").distinct()


def _settled(links: DataFrame) -> bool:
    """Whether every a has one b, and no b is an a: then each component is a star around its smallest."""
    ends = links.select(F.col("a").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down")).union(links.select("b", F.lit(0), F.lit(1)))
    sums = ends.groupBy("node").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return sums.where("up > 1 or up = 1 and down = 1").isEmpty()


def components(links: DataFrame) -> DataFrame:
    """Links (a, b) to one row (a, b) for each a that is not the smallest of its component b.

    Alternates large-star and small-star steps, which keep the components and need
    a number of rounds that grows with the logarithm of the size. Every step is a
    stored table, which goes when the next one stands; only its number of links and
    whether it is the last reach the driver. The hub of a large component is dealt
    over many tasks.
    """
    now = materialize(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    while not _settled(now):
        for step in (_large_star, _small_star):
            old, now = now, materialize(step(now))
            discard(old)
    return now
