"""Arrivals of messages, recovery of the gradient, time and traffic of a round.

One relational form serves every scheme: the first arrival of each code, the ``need``-th
smallest of these in each cluster (or the first plain average there, if earlier), the
slowest cluster.  Lists are bounded by workers times load, whatever the number of trials;
everything else is grouped by trial.  Times are integer microseconds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def arrivals(lat: DataFrame, msgs: DataFrame, comm: DataFrame | None = None, overlap: bool = True, keys: tuple[str, ...] = ()) -> DataFrame:
    """trial, worker, step, code, at (and scheme columns): when each message reaches the coordinator.

    ``lat``: trial, worker, unit, start (and ``keys``); a message leaves after ``needs`` computations.
    ``comm``: trial, worker, step, x.  With ``overlap`` a message goes out when it is ready and the one
    before has been received; the recursion max(ready, previous) + x is a running maximum of
    ready - (sum of earlier x), plus the sum up to here.
    """
    group = [*keys, "trial", "worker"]
    rows = lat.join(F.broadcast(msgs), "worker").withColumn("ready", F.col("start") + F.col("unit") * F.col("needs"))
    if comm is None:
        return rows.withColumn("at", F.col("ready"))
    rows = rows.join(comm, ["trial", "worker", "step"])
    if not overlap:
        return rows.withColumn("at", F.col("ready") + F.col("x"))
    # rows of one message share its x, so they are placed by the message's own ordinal
    order = Window.partitionBy("sid", *group).orderBy("step")
    spent = F.sum(F.when(F.col("first") == 1, F.col("x")).otherwise(0)).over(order.rangeBetween(Window.unboundedPreceding, 0))
    rows = rows.withColumn("spent", spent)
    slack = F.max(F.col("ready") - (F.col("spent") - F.col("x"))).over(order.rangeBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("at", F.col("spent") + slack).drop("spent")


def congested(arr: DataFrame, service: int, keys: tuple[str, ...] = (), groups: int = 1) -> DataFrame:
    """One receiver (or one for each of ``groups`` of neighbouring workers, then one for all): messages are served first come, first served.

    The queue's recursion is the same running maximum.  First order: a message held up here does not delay its sender.
    """
    def queue(rows: DataFrame, by: list[str]) -> DataFrame:
        order = Window.partitionBy(*by).orderBy("at", "worker", "step", "code").rowsBetween(Window.unboundedPreceding, 0)
        served = F.sum(F.col("first") * service).over(order)
        rows = rows.withColumn("served", served)
        wait = F.max(F.col("at") - (F.col("served") - F.col("first") * service)).over(order)
        return rows.withColumn("at", F.col("served") + wait).drop("served")

    base = ["sid", *keys, "trial"]
    if groups > 1:
        arr = queue(arr.withColumn("hub", F.pmod("worker", F.lit(groups))), [*base, "hub"]).drop("hub")
    return queue(arr, base)


def complete(arr: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """sid, scheme, keys, trial, t, load: the end of the round, and the messages that came by then (duplicates included)."""
    base = ["sid", "scheme", *keys, "trial"]
    first = arr.groupBy(*base, "cluster", "need", "code").agg(F.min("at").alias("at"), F.max("full").alias("full"))
    nth = first.groupBy(*base, "cluster", "need").agg(
        F.sort_array(F.collect_list(F.when(F.col("full") == 0, F.col("at")))).alias("ats"),
        F.min(F.when(F.col("full") == 1, F.col("at"))).alias("whole"),
    )
    ended = nth.groupBy(*base).agg(F.max(F.least(F.get("ats", F.col("need") - 1), F.col("whole"))).alias("t"))
    traffic = arr.where("first = 1").join(ended, base).groupBy(*base, "t").agg(F.count(F.when(F.col("at") <= F.col("t"), 1)).alias("load"))
    return traffic.select(*base, "t", "load")


def first_copies(arr: DataFrame) -> DataFrame:
    """The earliest copy of every code of a trial; later ones are dropped (map-side, no sort)."""
    best = F.min(F.struct("at", "worker", "step")).alias("b")
    return arr.groupBy("sid", "trial", "code").agg(best).select("sid", "trial", "code", F.col("b.at").alias("at"), F.col("b.worker").alias("worker"), F.col("b.step").alias("step"))


def missing_batches(arr: DataFrame, ended: DataFrame, K: int) -> DataFrame:
    """sid, trial, batch: mini-batches not received when the round ended (uncoded schemes)."""
    every = ended.select("sid", "trial").withColumn("batch", F.explode(F.sequence(F.lit(0), F.lit(K - 1))))
    got = arr.join(ended.select("sid", "trial", "t"), ["sid", "trial"]).where("at <= t").select("sid", "trial", F.col("code").alias("batch")).distinct()
    return every.join(got, ["sid", "trial", "batch"], "left_anti")


def relaunched(lat: DataFrame, at: int, keys: tuple[str, ...] = ()) -> DataFrame:
    """One batch a worker; at time ``at`` the i-th fastest finished worker repeats the i-th slowest open batch."""
    group = [*keys, "trial"]
    own = lat.withColumn("own", F.col("start") + F.col("unit"))
    done = F.col("own") <= at
    slow = F.row_number().over(Window.partitionBy(*group, done).orderBy(F.col("own").desc(), "worker"))
    fast = F.row_number().over(Window.partitionBy(*group, done).orderBy("own", "worker"))
    ranked = own.withColumn("done", done).withColumn("place", F.when(done, fast).otherwise(slow))
    helpers = ranked.where("done").select(*group, "place", (F.lit(at) + F.col("unit")).alias("help"))
    ends = ranked.where("not done").join(helpers, [*group, "place"], "left").select(*group, F.least("own", "help").alias("end"))
    both = ends.union(ranked.where("done").select(*group, F.col("own").alias("end")))
    return both.groupBy(*group).agg(F.max("end").alias("t"))


def summarise(done: DataFrame, by: list[str]) -> DataFrame:
    """Means over trials: avg_t in microseconds (integer division of sums), avg_load in thousandths, trials."""
    return done.groupBy(*by).agg(F.expr("sum(t) div count(*)").alias("avg_t"), F.expr("sum(load) * 1000 div count(*)").alias("avg_load"), F.count("*").alias("trials"))


def reductions(summary: DataFrame, baseline: str, by: list[str]) -> DataFrame:
    """Per cent by which each scheme's mean time is below the baseline's, under equal parameters."""
    base = summary.where(F.col("scheme") == baseline).select(*by, F.col("avg_t").alias("base_t"))
    return summary.join(base, by).select("scheme", *by, "avg_t", "base_t", F.round((F.col("base_t") - F.col("avg_t")) * 100.0 / F.col("base_t"), 4).alias("reduction"))


def waste(arr: DataFrame, ended: DataFrame, lat: DataFrame, r: int) -> DataFrame:
    """sid, trial, executed, useful: computations run by the end of the round, and those whose batch had not come before."""
    joined = lat.join(ended.select("sid", "trial", "t"), "trial")
    run = F.least(F.greatest(F.floor((F.col("t") - F.col("start")) / F.col("unit")), F.lit(0)), F.lit(r))
    executed = joined.groupBy("sid", "trial").agg(F.sum(run).cast("bigint").alias("executed"))
    useful = first_copies(arr).join(ended.select("sid", "trial", "t"), ["sid", "trial"]).where("at <= t").groupBy("sid", "trial").agg(F.count("*").alias("useful"))
    return executed.join(useful, ["sid", "trial"])


def traffic_bytes(load: Column, d: int) -> Column:
    """A message is as long as the parameter vector, in doubles."""
    return load * d * 8
