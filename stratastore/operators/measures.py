"""Costs in bytes and what is made of them. A pair costs its key (32 bytes) and its value."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

REF = 32


def pair_cost(size: Column) -> Column:
    return size + F.lit(REF)


def distinct_nodes(nodes: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by…, key, size): each key once within each group."""
    return nodes.groupBy(*(by or []), "key").agg(F.first("size").alias("size"))


def storage_cost(nodes: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by…, pairs, cost) of a store that holds the nodes."""
    return distinct_nodes(nodes, by).groupBy(*(by or [])).agg(F.count("*").alias("pairs"), F.sum(pair_cost(F.col("size"))).alias("cost"))


def added_cost(before: DataFrame, after: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by…, pairs, cost) of the keys of after that before does not hold."""
    keys = [*(by or []), "key"]
    return storage_cost(after.join(before.select(*keys).distinct(), keys, "left_anti"), by)


def expansion_factor(grid: DataFrame, lengths: DataFrame) -> DataFrame:
    """(content_id, scheme, s, cost, n, expansion): each content alone in an empty store. grid: build_grid's rows."""
    cost = grid.groupBy("content_id", "scheme", "s").agg(F.sum(pair_cost(F.col("size"))).alias("cost"))
    return cost.join(lengths.select("content_id", "n"), "content_id").withColumn("expansion", F.col("cost") / F.col("n"))


def cumulative_cost(grid: DataFrame, by: list[str]) -> DataFrame:
    """(by…, version, added, cost) after each version: a key counts from the first version that has it.

    One exchange by key with partial sums; no loop over versions, no store in between.
    """
    first = grid.groupBy(*by, "key").agg(F.min("version").alias("version"), F.first("size").alias("size"))
    per = first.groupBy(*by, "version").agg(F.sum(pair_cost(F.col("size"))).alias("added"))
    have = grid.select(*by, "version").distinct().join(per, [*by, "version"], "left").withColumn("added", F.coalesce("added", F.lit(0)).cast("long"))
    return have.withColumn("cost", F.sum("added").over(Window.partitionBy(*by).orderBy("version").rowsBetween(Window.unboundedPreceding, 0)))


def break_even(left: DataFrame, right: DataFrame, by: list[str], factor: float = 1.0) -> DataFrame:
    """(by…, version): the first version from which left costs at most factor times right. Both: by…, version, cost."""
    f = Fraction(factor).limit_denominator(1000)
    both = left.select(*by, "version", F.col("cost").alias("a")).join(right.select(*by, "version", F.col("cost").alias("b")), [*by, "version"])
    return both.where(F.col("a") * f.denominator <= F.col("b") * f.numerator).groupBy(*by).agg(F.min("version").alias("version"))


def dedup_ratio(nodes: DataFrame, bytes_in: DataFrame, by: list[str] | None = None) -> DataFrame:
    """(by…, bytes_in, cost, ratio, saved)."""
    total = bytes_in.groupBy(*(by or [])).agg(F.sum("n").alias("bytes_in"))
    cost = storage_cost(nodes, by)
    joined = total.join(cost, by) if by else total.crossJoin(cost)
    return joined.select(*(by or []), "bytes_in", "cost", (F.col("bytes_in") / F.col("cost")).alias("ratio"), (1 - F.col("cost") / F.col("bytes_in")).alias("saved"))


def dedup_overhead(nodes: DataFrame, bytes_in: DataFrame) -> DataFrame:
    """(cost, bytes_in, overhead)."""
    return bytes_in.agg(F.sum("n").alias("bytes_in")).crossJoin(storage_cost(nodes)).select("cost", "bytes_in", (F.col("cost") - F.col("bytes_in")).alias("overhead"))


def level_profile(nodes: DataFrame) -> DataFrame:
    """(level, nodes, distinct_nodes, avg_length, avg_size, avg_children)."""
    return nodes.groupBy("level").agg(
        F.count("*").alias("nodes"), F.countDistinct("key").alias("distinct_nodes"),
        F.avg(F.col("end_pos") - F.col("start_pos")).alias("avg_length"), F.avg("size").alias("avg_size"), F.avg("children").alias("avg_children"),
    )


def loess(samples: DataFrame, by: list[str], x: str, y: str, span: float = 0.75) -> DataFrame:
    """(by…, x, fit): local quadratic regression at each distinct x, tricube weights over the nearest span of the points.

    Samples are experiment cells: few. The normal equations are solved in closed form.
    """
    points = samples.select(*by, F.col(x).cast("double").alias("px"), F.col(y).cast("double").alias("py"))
    at = points.select(*by, F.col("px").alias("x0")).distinct()
    total = points.groupBy(*by).agg(F.count("*").alias("total"))
    pairs = points.join(at, by).join(total, by) if by else points.crossJoin(at).crossJoin(total)
    near = Window.partitionBy(*by, "x0").orderBy(F.abs(F.col("px") - F.col("x0")), "px", "py")
    k = F.greatest(F.ceil(F.col("total") * span), F.lit(1))
    ranked = pairs.withColumn("rank", F.row_number().over(near)).where(F.col("rank") <= k).withColumn("d", F.abs(F.col("px") - F.col("x0")))
    reach = F.max("d").over(Window.partitionBy(*by, "x0"))
    u = F.when(F.col("reach") > 0, F.col("d") / F.col("reach") / 1.0000001).otherwise(F.lit(0.0))
    w = F.pow(1 - F.pow(u, F.lit(3)), F.lit(3))
    # in units of the reach, so that the sums are of like size
    t = F.when(F.col("reach") > 0, (F.col("px") - F.col("x0")) / F.col("reach")).otherwise(F.lit(0.0))
    weighted = ranked.withColumn("reach", reach).select(*by, "x0", "py", w.alias("w"), t.alias("t"))
    moment = [F.sum(F.col("w") * F.pow("t", F.lit(float(i)))).alias(f"s{i}") for i in range(5)]
    rhs = [F.sum(F.col("w") * F.col("py") * F.pow("t", F.lit(float(i)))).alias(f"b{i}") for i in range(3)]
    m = weighted.groupBy(*by, "x0").agg(*moment, *rhs)
    c = {n: F.col(n) for n in (*[f"s{i}" for i in range(5)], *[f"b{i}" for i in range(3)])}
    det3 = c["s0"] * (c["s2"] * c["s4"] - c["s3"] * c["s3"]) - c["s1"] * (c["s1"] * c["s4"] - c["s2"] * c["s3"]) + c["s2"] * (c["s1"] * c["s3"] - c["s2"] * c["s2"])
    top3 = c["b0"] * (c["s2"] * c["s4"] - c["s3"] * c["s3"]) - c["s1"] * (c["b1"] * c["s4"] - c["b2"] * c["s3"]) + c["s2"] * (c["b1"] * c["s3"] - c["b2"] * c["s2"])
    det2 = c["s0"] * c["s2"] - c["s1"] * c["s1"]
    top2 = c["b0"] * c["s2"] - c["b1"] * c["s1"]
    fit = F.when(F.abs(det3) > 1e-9, top3 / det3).when(F.abs(det2) > 1e-9, top2 / det2).otherwise(c["b0"] / c["s0"])
    return m.select(*by, F.col("x0").alias(x), fit.alias("fit"))


def boxplot(samples: DataFrame, by: list[str], y: str) -> DataFrame:
    """(by…, samples, q1, q2, q3, low, high, outliers): whiskers reach the last points within 1.5 box lengths."""
    q = samples.groupBy(*by).agg(F.count("*").alias("samples"), F.percentile(y, 0.25).alias("q1"), F.percentile(y, 0.5).alias("q2"), F.percentile(y, 0.75).alias("q3"))
    reach = 1.5 * (F.col("q3") - F.col("q1"))
    own = samples.join(q, by).withColumn("inside", F.col(y).between(F.col("q1") - reach, F.col("q3") + reach))
    return own.groupBy(*by, "samples", "q1", "q2", "q3").agg(
        F.min(F.when(F.col("inside"), F.col(y))).alias("low"), F.max(F.when(F.col("inside"), F.col(y))).alias("high"), F.sum((~F.col("inside")).cast("long")).alias("outliers")
    )


def best_chunk_size(costs: DataFrame, by: list[str]) -> DataFrame:
    """(by…, s, cost): the cheapest chunk size; of equal ones the smallest."""
    best = costs.groupBy(*by).agg(F.min(F.struct("cost", "s")).alias("b"))
    return best.select(*by, F.col("b.s").alias("s"), F.col("b.cost").alias("cost"))


def summarise_runs(samples: DataFrame, by: list[str], y: str) -> DataFrame:
    """(by…, runs, mean, deviation, least, most)."""
    return samples.groupBy(*by).agg(F.count("*").alias("runs"), F.avg(y).alias("mean"), F.stddev(y).alias("deviation"), F.min(y).alias("least"), F.max(y).alias("most"))


def bound_check(samples: DataFrame, by: list[str], y: str, bound: str) -> DataFrame:
    """(by…, samples, under, mean, mean_bound, holds): whether the mean is under the model's bound."""
    out = samples.groupBy(*by).agg(F.count("*").alias("samples"), F.avg((F.col(y) <= F.col(bound)).cast("int")).alias("under"), F.avg(y).alias("mean"), F.avg(bound).alias("mean_bound"))
    return out.withColumn("holds", F.col("mean") <= F.col("mean_bound"))
