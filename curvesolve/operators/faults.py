"""Fault schedules, slice states, rebuilding of lost slices, and recoverability."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.uniform import hash32, uniform


def grid_of(spark: SparkSession, runs: int, cycles: int, p: int) -> DataFrame:
    """(run, cycle, sub) from one range."""
    n = F.col("id")
    return spark.range(runs * cycles * p).select(
        F.floor(n / (cycles * p)).cast("int").alias("run"), (F.floor(n / p) % cycles).cast("int").alias("cycle"), (n % p).cast("int").alias("sub"))


def bernoulli(spark: SparkSession, p: int, cycles: int, p_fault: float, seed: int = 1, runs: int = 1) -> DataFrame:
    """(run, cycle, sub, failed): independent failures."""
    return grid_of(spark, runs, cycles, p).withColumn("failed", uniform(seed, F.col("run"), F.col("cycle"), F.col("sub")) < p_fault)


def weibull(spark: SparkSession, p: int, cycles: int, shape: float, scale: float, seed: int = 1) -> DataFrame:
    """Failures at cumulated Weibull inter-arrival times, in units of cycles."""
    draws = grid_of(spark, 1, cycles, p).select("run", "sub", F.col("cycle").alias("k"), (
        scale * F.pow(-F.ln(1 - uniform(seed, "w", F.col("sub"), F.col("cycle"))), F.lit(1.0 / shape))).alias("gap"))
    by = Window.partitionBy("run", "sub").orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    hits = draws.withColumn("at", F.sum("gap").over(by)).where(F.col("at") < cycles).select("run", "sub", F.floor("at").cast("int").alias("cycle")).distinct()
    return grid_of(spark, 1, cycles, p).join(hits.withColumn("failed", F.lit(True)), ["run", "cycle", "sub"], "left").select(
        "run", "cycle", "sub", F.coalesce("failed", F.lit(False)).alias("failed"))


def from_events(events: DataFrame, p: int, cycle_seconds: int = 3600) -> DataFrame:
    """(cycle, sub, failed) of a log: a slice fails in a cycle that holds an error of its users."""
    cycle = F.floor(F.unix_seconds(F.col("ts").cast("timestamp")) / F.lit(cycle_seconds)).cast("long")
    return events.groupBy(cycle.alias("cycle"), F.pmod("user_id", F.lit(p)).cast("int").alias("sub")).agg(F.bool_or(F.col("event_type") == "error").alias("failed"))


def fixed_size(spark: SparkSession, p: int, cycles: int, lost: int, seed: int = 1) -> DataFrame:
    """Exactly ``lost`` random failures a cycle."""
    ranked = grid_of(spark, 1, cycles, p).withColumn("r", F.row_number().over(Window.partitionBy("run", "cycle").orderBy(hash32(seed, "f", F.col("cycle"), F.col("sub")), "sub")))
    return ranked.select("run", "cycle", "sub", (F.col("r") <= lost).alias("failed"))


def outages(schedule: DataFrame, length: int) -> DataFrame:
    """Each failure lasts ``length`` cycles."""
    by = Window.partitionBy("run", "sub").orderBy("cycle").rangeBetween(-(length - 1), 0)
    return schedule.withColumn("failed", F.max("failed").over(by))


def states(schedule: DataFrame) -> DataFrame:
    """Adds ``state``: failed; returning if it failed the cycle before; else active."""
    before = F.lag("failed", 1, False).over(Window.partitionBy("run", "sub").orderBy("cycle"))
    return schedule.withColumn("state", F.when(F.col("failed"), "failed").when(before, "returning").otherwise("active"))


def donors(held: DataFrame, failed: DataFrame, p: int, rule: str = "forward") -> DataFrame:
    """(cycle, lost_sub, pos, donor): who gives each lost position back.

    ``failed`` is (cycle, sub) of lost slices. Donors hold the position and are healthy in the cycle;
    the first one along the order from the lost slice on, or with rule "lowest" from slice 0 on.
    """
    lost = failed.select("cycle", F.col("sub").alias("lost_sub")).join(held.select(F.col("sub").alias("lost_sub"), "pos"), "lost_sub")
    others = held.select(F.col("sub").alias("donor"), "pos")
    dead = failed.select(F.col("cycle").alias("c"), F.col("sub").alias("d"))
    offer = lost.join(others, "pos").where("donor <> lost_sub").join(dead, (F.col("cycle") == F.col("c")) & (F.col("donor") == F.col("d")), "left_anti")
    far = F.pmod(F.col("donor") - F.col("lost_sub"), F.lit(p)) if rule == "forward" else F.col("donor")
    return offer.groupBy("cycle", "lost_sub", "pos").agg(F.min_by("donor", far).alias("donor"))


def rebuild(state: DataFrame, plan: DataFrame) -> DataFrame:
    """(cycle, sub, pos, v): the lost slices' values, copied from their donors' rows of ``state`` (sub, pos, v)."""
    return plan.join(state.select(F.col("sub").alias("donor"), "pos", "v"), ["donor", "pos"]).select("cycle", F.col("lost_sub").alias("sub"), "pos", "v")


def recoverable(schedule: DataFrame, p: int, gamma: float) -> DataFrame:
    """(run, cycle, ok): no floor(2 gamma) + 1 cyclically adjacent slices fail together."""
    need = int(2 * gamma) + 1
    by = Window.partitionBy("run", "cycle").orderBy("at")
    ring = schedule.where("failed").select("run", "cycle", F.explode(F.array(F.col("sub"), F.col("sub") + p)).alias("at"))
    runs = ring.withColumn("island", F.col("at") - F.row_number().over(by)).groupBy("run", "cycle", "island").count()
    longest = runs.groupBy("run", "cycle").agg(F.max("count").alias("n"))
    every = schedule.select("run", "cycle").distinct()
    return every.join(longest, ["run", "cycle"], "left").select("run", "cycle", (F.coalesce("n", F.lit(0)) < need).alias("ok"))


def recoverable_by_position(schedule: DataFrame, held: DataFrame) -> DataFrame:
    """The same from the covers: every position keeps a healthy holder. Also right for any overlap."""
    alive = schedule.join(held.select("sub", "pos"), "sub").groupBy("run", "cycle", "pos").agg(F.bool_or(~F.col("failed")).alias("alive"))
    return alive.groupBy("run", "cycle").agg(F.bool_and("alive").alias("ok"))


def assign_random(spark: SparkSession, problems: int, cycles: int, seed: int = 1) -> DataFrame:
    """(cycle, problem, worker): a random one-to-one assignment each cycle."""
    base = grid_of(spark, 1, cycles, problems)
    order = F.row_number().over(Window.partitionBy("cycle").orderBy(hash32(seed, "a", F.col("cycle"), F.col("sub")), "sub")) - 1
    return base.select("cycle", F.col("sub").alias("problem"), order.alias("worker"))


def neighbour_takeover(schedule: DataFrame, p: int) -> DataFrame:
    """(run, cycle, sub, failed, done_by, delay): a failed solve is done by the next slice, one solve later."""
    return schedule.select("run", "cycle", "sub", "failed", F.when(F.col("failed"), F.pmod(F.col("sub") + 1, F.lit(p))).otherwise(F.col("sub")).cast("int").alias("done_by"), F.col("failed").cast("int").alias("delay"))


def stats(schedule: DataFrame) -> DataFrame:
    """(run, cycle, failures, p_k) and running means of p_k and its square."""
    per = schedule.groupBy("run", "cycle").agg(F.count_if("failed").alias("failures"), F.count_if(~F.col("failed")).alias("p_k"))
    by = Window.partitionBy("run").orderBy("cycle").rowsBetween(Window.unboundedPreceding, 0)
    return per.withColumn("mean_p_k", F.avg("p_k").over(by)).withColumn("mean_p_k2", F.avg(F.col("p_k") * F.col("p_k")).over(by))


def average_runs(history: DataFrame) -> DataFrame:
    """(k, err, runs): mean error of the runs that lost nothing for good."""
    lost = history.where(~F.col("ok")).select("run_id").distinct()
    return history.join(lost, "run_id", "left_anti").groupBy("k").agg(F.avg("err").alias("err"), F.count("*").alias("runs"))
