"""Measures over run traces and results. A trace has a row per round: see schemas.TRACE; round 0 is the load."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F
from pyspark.sql.window import Window

RUN = ["problem", "engine", "graph"]


def mean_round_ms(trace: DataFrame) -> DataFrame:
    """Total time of a run over its rounds: the load counts, as the start of each iteration does."""
    return trace.groupBy(*RUN).agg((F.sum("ms") / F.max("round")).alias("mean_ms"), F.max("round").cast("long").alias("rounds"))


def cumulative_ms(trace: DataFrame) -> DataFrame:
    so_far = Window.partitionBy("run_id").orderBy("round").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return trace.select("run_id", *RUN, "round", F.sum("ms").over(so_far).alias("total_ms"))


def linear_fit(trace: DataFrame) -> DataFrame:
    """Least squares of total time on the round, from round 1."""
    total = cumulative_ms(trace).where("round > 0")
    y, x = F.col("total_ms").cast("double"), F.col("round").cast("double")
    return total.groupBy("run_id", *RUN).agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def first_round_ratio(trace: DataFrame) -> DataFrame:
    """Load and first round against the mean of the others."""
    first = F.sum(F.when(F.col("round") <= 1, F.col("ms")))
    return trace.groupBy("run_id", *RUN).agg((first / F.nullif(F.avg(F.when(F.col("round") > 1, F.col("ms"))), F.lit(0.0))).alias("ratio"))


def speedup(trace: DataFrame, base: str = "reshuffle") -> DataFrame:
    """Each engine against ``base`` on the same problem and graph: times as fast, percent less time."""
    mean = mean_round_ms(trace)
    ref = mean.where(F.col("engine") == base).select("problem", "graph", F.col("mean_ms").alias("base_ms"))
    return mean.join(ref, ["problem", "graph"]).select(*RUN, (F.col("base_ms") / F.col("mean_ms")).alias("times"), ((1 - F.col("mean_ms") / F.col("base_ms")) * 100).alias("percent_less"))


def scale_out(trace: DataFrame, near: float = 0.05) -> DataFrame:
    """Per worker count: time against the fewest workers, and whether it is the smallest count near the best."""
    mean = trace.groupBy(*RUN, "cores").agg((F.sum("ms") / F.max("round")).alias("mean_ms"))
    run = Window.partitionBy(*RUN)
    mean = mean.withColumn("factor", F.first_value("mean_ms").over(run.orderBy("cores")) / F.col("mean_ms")).withColumn("best", F.min("mean_ms").over(run))
    close = F.when(F.col("mean_ms") <= (1 + near) * F.col("best"), F.col("cores"))
    return mean.withColumn("enough_cores", F.min(close).over(run)).drop("best")


def size_fit(trace: DataFrame, sizes: DataFrame) -> DataFrame:
    """R2 of mean time on vertices and on edges, per problem and engine; ``sizes`` is (graph, vertices, edges)."""
    rows = mean_round_ms(trace).join(F.broadcast(sizes), "graph")
    return rows.groupBy("problem", "engine").agg(F.regr_r2("mean_ms", F.col("vertices").cast("double")).alias("r2_vertices"), F.regr_r2("mean_ms", F.col("edges").cast("double")).alias("r2_edges"))


def break_even(trace: DataFrame, engine: str = "resident", base: str = "reshuffle") -> DataFrame:
    """First round at which ``engine`` has taken no more time in all than ``base``."""
    total = cumulative_ms(trace).where("round > 0")
    a, b = (total.where(F.col("engine") == e).select("problem", "graph", "round", F.col("total_ms").alias(c)) for e, c in ((engine, "a"), (base, "b")))
    return a.join(b, ["problem", "graph", "round"]).groupBy("problem", "graph").agg(F.min(F.when(F.col("a") <= F.col("b"), F.col("round"))).alias("break_even"))


def round_delta(trace: DataFrame) -> DataFrame:
    order = Window.partitionBy("run_id").orderBy("round")
    return trace.select("run_id", *RUN, "round", (F.col("ms") - F.lag("ms").over(order)).alias("delta_ms"))


def smoothed_ms(trace: DataFrame, k: int = 2) -> DataFrame:
    return trace.select("run_id", *RUN, "round", F.avg("ms").over(Window.partitionBy("run_id").orderBy("round").rowsBetween(-k, 0)).alias("smooth_ms"))


def trace_cube(trace: DataFrame) -> DataFrame:
    return trace.cube(*RUN).agg(F.sum("ms").alias("ms"), F.grouping_id().cast("long").alias("level"))


def wide(trace: DataFrame, engines: list[str]) -> DataFrame:
    return trace.groupBy("problem", "graph").pivot("engine", engines).agg(F.sum("ms"))


def agreement(a: DataFrame, b: DataFrame, value: str) -> DataFrame:
    """One row: vertices on both sides, on one only, null on one only, and the largest absolute difference."""
    x = a.select("id", F.col(value).cast("double").alias("x"), F.lit(True).alias("in_a"))
    y = b.select("id", F.col(value).cast("double").alias("y"), F.lit(True).alias("in_b"))
    both = x.join(y, "id", "full")
    one = F.col("in_a").isNull() | F.col("in_b").isNull()
    return both.agg(F.count("*").alias("vertices"), F.sum(one.cast("long")).alias("one_side"), F.sum((F.col("x").isNull() != F.col("y").isNull()).cast("long")).alias("null_on_one"), F.coalesce(F.max(F.abs(F.col("x") - F.col("y"))), F.lit(0.0)).alias("max_difference"))


def spread(state: DataFrame) -> DataFrame:
    """How far likelihoods still differ: 0 once all labels have washed out."""
    return state.agg((F.max("p") - F.min("p")).alias("spread"), F.avg("p").alias("mean"))


def holdout_scores(decided: DataFrame, truth: DataFrame, hidden: DataFrame) -> DataFrame:
    """One row over the hidden vertices: how many, share given a class, share of those right, macro F1."""
    rows = hidden.select("id").join(truth.select("id", F.col("class").alias("real")), "id").join(decided.select("id", F.col("class").alias("said")), "id", "left")
    base = rows.agg(F.count("*").alias("hidden"), F.count("said").alias("labelled"), F.sum((F.col("said") == F.col("real")).cast("long")).alias("right"))
    real = rows.groupBy(F.col("real").alias("class")).agg(F.count("*").alias("n_real"), F.sum((F.col("said") == F.col("real")).cast("long")).alias("hit"))
    said = rows.where("said is not null").groupBy(F.col("said").alias("class")).agg(F.count("*").alias("n_said"))
    per = real.join(said, "class", "full")
    f1 = per.agg(F.avg(2 * F.coalesce("hit", F.lit(0)) / (F.coalesce("n_real", F.lit(0)) + F.coalesce("n_said", F.lit(0)))).alias("macro_f1"))
    return base.join(f1).select("hidden", "labelled", "right", (F.col("labelled") / F.col("hidden")).alias("coverage"), (F.col("right") / F.nullif(F.col("labelled"), F.lit(0))).alias("accuracy"), "macro_f1")  # one row beside one row


def confusion(decided: DataFrame, truth: DataFrame) -> DataFrame:
    return truth.select("id", F.col("class").alias("real")).join(decided.select("id", F.col("class").alias("said")), "id", "left").groupBy("real", "said").agg(F.count("*").alias("n"))


def brier(state: DataFrame, truth: DataFrame) -> DataFrame:
    """Mean squared gap between likelihood and a 0/1 truth ``(id, y)``."""
    return state.join(truth, "id").where("p is not null").agg(F.avg(F.pow(F.col("p") - F.col("y"), F.lit(2))).alias("brier"))
