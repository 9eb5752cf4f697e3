"""Mini-batches in hash order: without replacement within an epoch, the same on every run."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def per_epoch(n: int, size: int) -> int:
    return max(1, n // size)


def place(sample: Column, seed: int, epoch: Column, per: int) -> Column:
    """A sample's place in an epoch: the first 32 bits of an md5 digest, modulo the number of batches."""
    digest = F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), sample.cast("string")))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % per


def draw(cells: DataFrame, size: int, n: int, seed: int = 7, step: int = 0) -> DataFrame:
    """CELLS of the ``step``-th batch of about ``size`` of n samples.

    A sample's place in its epoch is a hash, and a batch is a range of places: no sort and no shuffle; sizes are about even.
    """
    per = per_epoch(n, size)
    epoch, nth = divmod(step, per)
    return cells.where(place(F.col("sample_id"), seed, F.lit(epoch), per) == nth)


def draw_exact(samples: DataFrame, size: int, seed: int = 7, epoch: int = 0) -> DataFrame:
    """``(sample_id)`` of exactly ``size`` samples with the smallest md5, a top-k rather than a sort."""
    key = F.md5(F.concat_ws(":", F.lit(str(seed)), F.lit(str(epoch)), F.col("sample_id").cast("string")))
    return samples.select("sample_id").distinct().orderBy(key).limit(size)


def prefetch(cells: DataFrame, size: int, n: int, steps: int, seed: int = 7, first: int = 0) -> DataFrame:
    """CELLS of many batches with their ``step``, from one scan; a sample comes once for each epoch that the steps reach into."""
    per = per_epoch(n, size)
    epochs = F.explode(F.sequence(F.lit(first // per), F.lit((first + steps - 1) // per))).alias("epoch")
    step = (place(F.col("sample_id"), seed, F.col("epoch"), per) + F.col("epoch") * per).alias("step")
    return cells.select("*", epochs).select(*cells.columns, step).where(F.col("step").between(first, first + steps - 1))


def moments_by_step(fetched: DataFrame) -> DataFrame:
    """``(step, a, b, c)``: second moments of each batch that ``prefetch`` gives, over its samples with cells."""
    sizes = fetched.groupBy("step").agg(F.count_distinct("sample_id").alias("n"))
    x = fetched.select("step", "sample_id", F.col("node_id").alias("a"), F.col("x").alias("xa"))
    y = fetched.select("step", "sample_id", F.col("node_id").alias("b"), F.col("x").alias("xb"))
    sums = x.join(y, ["step", "sample_id"]).where("a <= b").groupBy("step", "a", "b").agg(F.sum(F.col("xa") * F.col("xb")).alias("s"))
    return sums.join(sizes, "step").select("step", "a", "b", (F.col("s") / F.col("n")).alias("c"))
