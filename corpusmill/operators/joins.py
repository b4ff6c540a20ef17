"""Joins that Spark has no single operator for: range, as-of and salted."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, on: list[str], at: str, near: str, width: int, names: tuple[str, str]) -> DataFrame:
    """Pairs of equal ``on`` whose integers ``left.at`` and ``right.near`` differ by ``width`` at most.

    The right side is cut into buckets of that width; each left row looks into
    three of them, so the join is an equi-join without a nested loop. ``names``
    are the payload structs of the result.
    """
    a = left.select(*on, F.col(at).alias("_at"), F.struct(*left.columns).alias(names[0]), F.floor(F.col(at) / width).alias("_b"))
    a = a.withColumn("_bucket", F.explode(F.array(F.col("_b") - 1, F.col("_b"), F.col("_b") + 1)))
    b = right.select(*on, F.col(near).alias("_near"), F.struct(*right.columns).alias(names[1]), F.floor(F.col(near) / width).alias("_bucket"))
    return a.join(b, [*on, "_bucket"]).where(F.abs(F.col("_at") - F.col("_near")) <= width).select(*on, *names)


def asof_join(left: DataFrame, right: DataFrame, by: list[str], time: str, value: str, name: str) -> DataFrame:
    """Each row of ``left`` with the last ``right.value`` of its key at or before its time.

    Both sides are united and one running window carries the last value on: one
    shuffle, no pairs.
    """
    rows = left.select(*by, time, F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_value"), F.lit(1).alias("_side"))
    marks = right.select(*by, time, F.lit(None).cast(rows.schema["_row"].dataType).alias("_row"), F.col(value).alias("_value"), F.lit(0).alias("_side"))
    run = Window.partitionBy(*by).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    carried = rows.unionByName(marks).withColumn(name, F.last("_value", ignorenulls=True).over(run))
    return carried.where("_side = 1").select("_row.*", name)


def beaten_counts(df: DataFrame, on: list[str], above: str, below: str, name: str) -> DataFrame:
    """Rows with the number of rows of equal ``on`` that have a smaller ``above`` and a larger integer ``below``, where there are any.

    No pairs are made. Equal rows are counted once. Values of ``above`` get a rank; of two
    ranks the larger has a one at the highest bit where they differ. So for each bit the
    rows that agree above it are sorted by ``below``, and each row with a one adds the
    running count of rows with a zero.
    """
    keys = [*on, above, below]
    cells = df.where(" and ".join(f"{k} is not null" for k in keys)).groupBy(*keys).agg(F.count("*").alias("_n"))
    ranks = F.dense_rank().over(Window.partitionBy(*on).orderBy(above)) - 1
    cells = cells.select("*", ranks.cast("long").alias("_r"))
    top = int(cells.agg(F.max("_r")).first()[0] or 0)
    bits = F.explode(F.sequence(F.lit(0), F.lit(max(1, top.bit_length()) - 1))).alias("_bit")
    deep = cells.select(*keys, "_n", "_r", bits).selectExpr(*keys, "_n", "_bit", "shiftright(_r, _bit + 1) as _same", "shiftright(_r, _bit) % 2 as _one")
    larger = Window.partitionBy(*on, "_bit", "_same").orderBy(F.desc(below)).rangeBetween(Window.unboundedPreceding, -1)
    met = deep.withColumn("_c", F.sum(F.when(F.col("_one") == 0, F.col("_n"))).over(larger)).where("_one = 1")
    counts = met.groupBy(*keys).agg(F.sum("_c").alias(name)).where(F.col(name) > 0)
    return df.join(counts, keys)


def salted_join(big: DataFrame, small: DataFrame, on: list[str], salts: int, salt: Column) -> DataFrame:
    """Inner join whose hot keys are spread over ``salts`` tasks; ``small`` is repeated that often."""
    a = big.withColumn("_salt", F.pmod(salt, F.lit(salts)).cast("int"))
    b = small.withColumn("_salt", F.explode(F.array(*[F.lit(k) for k in range(salts)])))
    return a.join(b, [*on, "_salt"]).drop("_salt")
