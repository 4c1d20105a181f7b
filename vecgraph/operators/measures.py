"""Cost and accuracy measures as DataFrame aggregations."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window, functions as F

TIE = 1e-6


def recall_at_k(hits: DataFrame, truth: DataFrame, k: int, by: list[str] | None = None) -> DataFrame:
    """Mean share of answers (qid, dist) no farther than the k-th exact distance; queries without answers count zero.

    Distances decide, so ties are fair to every method.
    """
    kth = truth.where(F.col("rank") <= k).groupBy("qid").agg(F.max("dist").alias("limit"), F.count("*").alias("want"))
    by = by or []
    groups = kth if not by else hits.select(*by).distinct().crossJoin(kth)  # one row for each setting and query
    good = hits.where(F.col("rank") <= k).join(kth, "qid").where(F.col("dist") <= F.col("limit") + TIE).groupBy(*by, "qid").agg(F.count("*").alias("got"))
    each = groups.join(good, [*by, "qid"], "left").withColumn("r", F.least(F.coalesce("got", F.lit(0)), F.col("want")) / F.col("want"))
    return each.groupBy(*by).agg(F.avg("r").alias("recall")) if by else each.agg(F.avg("r").alias("recall"))


def cost_report(hits: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Means of the counters over queries, and the share of checked neighbours that passed."""
    by = by or []
    one = hits.groupBy(*by, "qid").agg(*[F.max(c).alias(c) for c in ("n_checked", "n_pass", "n_exact", "n_visited", "n_fp", "n_fp_reused", "n_rounds")])
    return one.groupBy(*by).agg(
        *[F.avg(c).alias(c) for c in ("n_checked", "n_exact", "n_visited", "n_fp", "n_fp_reused", "n_rounds")],
        F.try_divide(F.sum("n_pass"), F.sum("n_checked")).alias("pass_ratio"),
    )


def tradeoff_curve(runs: DataFrame, cost: str = "n_exact") -> DataFrame:
    """``runs(method, recall, <cost>)`` that no run of the same method beats in recall at no more cost."""
    cheaper = Window.partitionBy("method").orderBy(cost, F.desc("recall")).rowsBetween(Window.unboundedPreceding, -1)
    return runs.withColumn("best", F.max("recall").over(cheaper)).where(F.col("best").isNull() | (F.col("recall") > F.col("best"))).drop("best")


def cost_at(runs: DataFrame, recall: float, cost: str = "n_exact") -> DataFrame:
    """(method, cost): the cost at a recall, between the two runs around it (on the curve)."""
    order = Window.partitionBy("method").orderBy("recall", cost)
    pairs = tradeoff_curve(runs, cost).select("method", "recall", F.col(cost).alias("c"), F.lead("recall").over(order).alias("r2"), F.lead(cost).over(order).alias("c2"))
    inside = pairs.where((F.col("recall") <= recall) & (F.col("r2") >= recall) | (F.col("recall") >= recall))
    at = F.when(F.col("recall") >= recall, F.col("c")).otherwise(F.col("c") + (F.col("c2") - F.col("c")) * (recall - F.col("recall")) / (F.col("r2") - F.col("recall")))
    return inside.groupBy("method").agg(F.min(at).alias("cost"))


def speedup_at(runs: DataFrame, recall: float, base: str, cost: str = "n_exact") -> DataFrame:
    """(method, speedup): the base method's cost over each method's, at equal recall."""
    each = cost_at(runs, recall, cost)
    of_base = each.where(F.col("method") == base).select(F.col("cost").alias("base_cost"))
    return each.crossJoin(F.broadcast(of_base)).select("method", (F.col("base_cost") / F.col("cost")).alias("speedup"))  # one row


def in_degrees(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    """(vec_id, in_degree) of every node; nodes that nobody points at have zero."""
    found = edges.groupBy(F.col("dst").alias("vec_id")).agg(F.count("*").alias("n"))
    return nodes.select("vec_id").join(found, "vec_id", "left").select("vec_id", F.coalesce("n", F.lit(0)).alias("in_degree"))


def unreachable(edges: DataFrame, nodes: DataFrame, entries: DataFrame) -> DataFrame:
    """Nodes that no path of edges reaches from the entries: a frontier loop over checkpointed tables, until nothing new is reached."""
    from ..sources.session import checkpoint

    reached = checkpoint(entries.select("vec_id").distinct())
    frontier = reached
    while True:
        step = edges.join(frontier.select(F.col("vec_id").alias("src")), "src", "left_semi").select(F.col("dst").alias("vec_id")).distinct()
        frontier = checkpoint(step.join(reached, "vec_id", "left_anti"))
        if frontier.isEmpty():
            break
        reached = checkpoint(reached.union(frontier))
    return nodes.select("vec_id").join(reached, "vec_id", "left_anti")


def confusion(sample: DataFrame, stat: str, truth: str) -> DataFrame:
    """Rates of a one-sided test: ``stat >= 0`` against ``truth`` (boolean)."""
    passed = F.col(stat) >= 0
    return sample.agg(
        F.count("*").alias("n"),
        F.avg(passed.cast("double")).alias("pass_ratio"),
        F.avg(F.when(F.col(truth), passed.cast("double"))).alias("pass_if_true"),
        F.avg(F.when(~F.col(truth), (~passed).cast("double"))).alias("reject_if_false"),
    )


def estimator_error(sample: DataFrame, estimate: str = "estimate", exact: str = "cos_exact") -> DataFrame:
    """Bias, root mean square error, correlation and covariance of an estimate."""
    e = F.col(estimate) - F.col(exact)
    return sample.agg(
        F.avg(e).alias("bias"), F.sqrt(F.avg(e * e)).alias("rmse"), F.corr(estimate, exact).alias("corr"), F.covar_samp(estimate, exact).alias("covar"), F.var_samp(e).alias("var")
    )


def block_balance(sample: DataFrame, blocks: int) -> DataFrame:
    """The largest deviations of block norms and block products from even shares, for unit ``edge`` and ``way`` arrays."""
    width = F.size("edge") / blocks
    part = lambda c: F.slice(F.col(c), (F.col("l") * width + 1).cast("int"), width.cast("int"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda u, v: u.cast("double") * v), F.lit(0.0), lambda s, v: s + v)
    each = sample.select("edge", "way", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("l"))
    root = math.sqrt(blocks)
    return each.select(
        F.abs(root * F.sqrt(dot(part("edge"), part("edge"))) - 1).alias("a"),
        F.abs(root * F.sqrt(dot(part("way"), part("way"))) - 1).alias("b"),
        F.abs(blocks * dot(part("edge"), part("way")) - dot(F.col("edge"), F.col("way"))).alias("c"),
    ).agg(F.max(F.greatest("a", "b", "c")).alias("eta"))


def cost_model(visited: Column | str, m: int, blocks: int, gamma: Column | str, dim: int) -> Column:
    """Operations of a gated search: n'ML + gamma M n' d (with 2M neighbours a node)."""
    v, g = (F.col(x) if isinstance(x, str) else x for x in (visited, gamma))
    return v * m * blocks + g * m * v * dim


def amortised_ratio(runs: DataFrame) -> DataFrame:
    """(method, ratio): mean cost of an insertion over mean cost of a search, ``runs(method, op, cost)``."""
    return runs.groupBy("method").agg((F.avg(F.when(F.col("op") == "insert", F.col("cost"))) / F.avg(F.when(F.col("op") == "search", F.col("cost")))).alias("ratio"))


def tier_methods(scores: DataFrame, tiers: int = 4) -> DataFrame:
    """``scores(criterion, method, score)``, higher better, cut in tiers at the widest gaps of their logarithms; the last tier is best."""
    by = Window.partitionBy("criterion")
    s = F.log(F.col("score"))
    gaps = scores.withColumn("gap", s - F.lag(s).over(by.orderBy("score", "method")))
    ranked = gaps.withColumn("place", F.row_number().over(by.orderBy(F.desc_nulls_last("gap"), "method")))
    steps = F.sum(F.when((F.col("place") < tiers) & (F.col("gap") > 0), 1).otherwise(0)).over(by.orderBy("score", "method"))
    out = ranked.withColumn("step", steps)
    return out.withColumn("tier", (F.lit(tiers) - F.max("step").over(by) + F.col("step")).cast("int")).select("criterion", "method", "score", "tier")


def robustness(runs: DataFrame, axis: str, ratio: str) -> DataFrame:
    """(method, slope, correlation) of a ratio over the logarithm of an axis."""
    x, y = F.log(axis), F.col(ratio)
    both = F.covar_samp(x, y)
    return runs.groupBy("method").agg(F.try_divide(both, F.var_samp(x)).alias("slope"), F.try_divide(both, F.stddev_samp(x) * F.stddev_samp(y)).alias("corr"))
