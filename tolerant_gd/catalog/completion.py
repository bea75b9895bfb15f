"""Queries over arrivals and completion of rounds, replayed in SQL on the same integer microseconds."""

from __future__ import annotations

from pyspark.sql import functions as F

from tolerant_gd.functions import latency
from tolerant_gd.functions.randoms import portable_sql
from tolerant_gd.operators import analytic, layout, recover
from tolerant_gd.plans.scheme import Scheme, message_threshold, messages, scheme
from tolerant_gd.sources.tables import fitted_times, measurements, read
from tolerant_gd.streaming import detector

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
TRIALS, WORKERS, SEED = 40, 20, 1

MEASURED = """m AS (SELECT worker, kind, row_number() OVER (PARTITION BY worker, kind ORDER BY event_id) - 1 AS idx, us FROM (
 SELECT CAST(user_id % 20 AS INT) AS worker, event_id, CASE WHEN event_type IN ('view', 'click', 'purchase') THEN 'comp' ELSE 'comm' END AS kind,
        CAST(round(CASE WHEN event_type IN ('view', 'click', 'purchase') THEN 500 + value * 20 ELSE value * 10 END) AS BIGINT) AS us FROM events)),
z AS (SELECT worker, kind, count(*) AS n FROM m GROUP BY ALL)"""

#: Computation times as shifted exponentials: of all workers together (fit), and of each (fits).
FIT = """c AS (SELECT CAST(user_id % 20 AS INT) AS worker, CAST(round(500 + value * 20) AS BIGINT) AS us FROM events WHERE event_type IN ('view', 'click', 'purchase')),
fit AS (SELECT min(us) AS shift, CAST(sum(us) // count(*) AS BIGINT) - min(us) AS excess FROM c),
fits AS (SELECT worker, min(us) AS shift, CAST(sum(us) // count(*) AS BIGINT) - min(us) AS excess FROM c GROUP BY worker)"""


def units_sql(trials: int = TRIALS) -> str:
    """CTEs m, z and u(trial, worker, unit)."""
    return f"""{MEASURED}, u AS (SELECT trial, g.worker, us AS unit FROM (SELECT t AS trial, CAST(w AS INT) AS worker, {portable_sql(str(SEED), "'u'", 't', 'w')} AS h FROM generate_series(0, {trials - 1}) a(t), generate_series(0, {WORKERS - 1}) b(w)) g
 JOIN z ON z.worker = g.worker AND z.kind = 'comp' JOIN m ON m.worker = g.worker AND m.kind = 'comp' AND m.idx = g.h % z.n)"""


def comm_sql(trials: int, steps: int, mean_us: int = 0) -> str:
    """CTE x(trial, worker, step, x)."""
    extra = f" + CAST(round(round(-ln(({portable_sql(str(SEED), chr(39) + 'e' + chr(39), 'trial', 'g.worker', 'step')} + 0.5) / 4503599627370496.0), 9) * {mean_us}.0) AS BIGINT)" if mean_us else ""
    return f"""x AS (SELECT trial, g.worker, step, us{extra} AS x FROM (SELECT t AS trial, CAST(w AS INT) AS worker, CAST(s AS INT) AS step, {portable_sql(str(SEED), "'c'", 't', 'w', 's')} AS h
 FROM generate_series(0, {trials - 1}) a(t), generate_series(0, {WORKERS - 1}) b(w), generate_series(0, {steps - 1}) c(s)) g
 JOIN z ON z.worker = g.worker AND z.kind = 'comm' JOIN m ON m.worker = g.worker AND m.kind = 'comm' AND m.idx = g.h % z.n)"""


def messages_sql(schemes: list[Scheme]) -> str:
    """CTE k: the message tables."""
    rows = ", ".join(f"({i}, '{s.label}', {m.worker}, {m.step}, {m.code}, {m.cluster}, {m.needs}, {int(m.full)}, {int(m.first)}, {message_threshold(s)})" for i, s in enumerate(schemes) for m in messages(s))
    return f"k(sid, scheme, worker, step, code, cluster, needs, full_, first_, need) AS (VALUES {rows})"


def complete_sql(arrivals: str, keys: tuple[str, ...] = ()) -> str:
    """The end of every round from a relation with the columns of k, trial, at and ``keys``."""
    base = ", ".join(["sid", "scheme", *keys, "trial"])
    return f"""a AS ({arrivals}), f AS (SELECT {base}, cluster, need, code, min(at_) AS at_, max(full_) AS full_ FROM a GROUP BY ALL),
r AS (SELECT *, row_number() OVER (PARTITION BY {base}, cluster, full_ ORDER BY at_) AS n FROM f),
c AS (SELECT {base}, cluster, least(min(at_) FILTER (full_ = 0 AND n = need), min(at_) FILTER (full_ = 1)) AS t FROM r GROUP BY ALL),
e AS (SELECT {base}, max(t) AS t FROM c GROUP BY ALL),
done AS (SELECT {base}, CAST(t AS BIGINT) AS t, count(*) FILTER (at_ <= t) AS load FROM a JOIN e USING ({base}) WHERE first_ = 1 GROUP BY ALL)"""


PLAIN = "SELECT k.*, u.trial, unit * needs AS at_ FROM u JOIN k USING (worker)"
SENT = """SELECT *, spent + max(ready - (spent - x)) OVER (PARTITION BY sid, trial, worker ORDER BY step RANGE UNBOUNDED PRECEDING) AS at_ FROM (
 SELECT k.*, u.trial, unit * needs AS ready, x, sum(CASE WHEN first_ = 1 THEN x ELSE 0 END) OVER (PARTITION BY sid, u.trial, k.worker ORDER BY k.step RANGE UNBOUNDED PRECEDING) AS spent
 FROM u JOIN k USING (worker) JOIN x ON x.trial = u.trial AND x.worker = k.worker AND x.step = k.step)"""

SCHEMES = {
    "wait_all": scheme("wait_all", 20),
    "gradcode_single": scheme("gradcode_single", 20, 4),
    "gradcode_repeat": scheme("gradcode_repeat", 20, 4),
    "gradcode_shared": scheme("gradcode_shared", 20, 4, order=3, P=4),
    "gradcode_layered": scheme("gradcode_layered", 20, 4, orders=(4, 3), P=4),
    "gradcode_hybrid": scheme("gradcode_hybrid", 20, 5, orders=(5, 3), P=4),
    "gradcode_clustered": scheme("gradcode_single", 20, 4, P=4),
    "lagrange_single": scheme("lagrange_single", 20, 4),
    "lagrange_multi": scheme("lagrange_multi", 20, 4),
    "lagrange_multi_2": scheme("lagrange_multi", 20, 4, polys=2),
    "uncoded_multi": scheme("uncoded_multi", 20, 4),
    "uncoded_partial": scheme("uncoded_partial", 20, 4, tolerance=0.1),
    "uncoded_single": scheme("uncoded_single", 20, 4),
    "first_workers": scheme("first_workers", 20, need=15),
    "backup_workers": scheme("backup_workers", 15, extra=5),
}


def done(s, d, schemes: list[Scheme], trials: int = TRIALS, steps: int = 0, mean_us: int = 0):
    lat = latency.measured_units(s, d, trials, WORKERS, SEED)
    comm = latency.measured_comm(s, d, trials, steps, WORKERS, SEED, mean_us) if steps else None
    return recover.complete(recover.arrivals(lat, layout.message_table(s, schemes), comm))


def _completion(name: str, sch: Scheme) -> None:
    steps = 1 + max(m.step for m in messages(sch))
    QUERIES[f"complete_{name}"] = lambda s, d: done(s, d, [sch], steps=steps).select("trial", "t", "load")
    ORACLES[f"complete_{name}"] = f"WITH {units_sql()}, {comm_sql(TRIALS, steps)}, {messages_sql([sch])}, {complete_sql(SENT)} SELECT trial, t, load FROM done"


for _name, _scheme in SCHEMES.items():
    _completion(_name, _scheme)

QUERIES["complete_relaunch"] = lambda s, d: recover.relaunched(latency.measured_units(s, d, TRIALS, WORKERS, SEED), 1500).select("trial", F.col("t").cast("bigint").alias("t"))
ORACLES["complete_relaunch"] = f"""WITH {units_sql()}, o AS (SELECT trial, worker, unit, unit <= 1500 AS done,
 CASE WHEN unit <= 1500 THEN row_number() OVER (PARTITION BY trial, unit <= 1500 ORDER BY unit, worker) ELSE row_number() OVER (PARTITION BY trial, unit <= 1500 ORDER BY unit DESC, worker) END AS place FROM u)
SELECT o.trial, CAST(max(CASE WHEN o.done THEN o.unit ELSE least(o.unit, coalesce(1500 + h.unit, o.unit)) END) AS BIGINT) AS t FROM o LEFT JOIN o h ON h.trial = o.trial AND h.done AND h.place = o.place GROUP BY o.trial"""

# Arrivals, copies, sets ------------------------------------------------------------------------

_MULTI = SCHEMES["uncoded_multi"]


def _arr(s, d, sch=_MULTI):
    lat = latency.measured_units(s, d, TRIALS, WORKERS, SEED)
    return recover.arrivals(lat, layout.message_table(s, [sch]))


QUERIES["first_copy_only"] = lambda s, d: recover.first_copies(_arr(s, d)).select("trial", "code", "at", "worker", "step")
ORACLES["first_copy_only"] = f"WITH {units_sql()}, {messages_sql([_MULTI])}, a AS ({PLAIN}) SELECT trial, code, at_ AS \"at\", worker, step FROM (SELECT *, row_number() OVER (PARTITION BY trial, code ORDER BY at_, worker, step) AS n FROM a) WHERE n = 1"
QUERIES["missing_batches"] = lambda s, d: _missing(s, d)
ORACLES["missing_batches"] = f"WITH {units_sql()}, {messages_sql([SCHEMES['uncoded_partial']])}, {complete_sql(PLAIN)} SELECT trial, CAST(b AS INT) AS batch FROM done, generate_series(0, 19) g(b) EXCEPT SELECT a.trial, code FROM a JOIN done USING (trial) WHERE at_ <= t"


def _missing(s, d):
    arr = _arr(s, d, SCHEMES["uncoded_partial"])
    return recover.missing_batches(arr, recover.complete(arr), 20).select("trial", "batch")


QUERIES["common_codes"] = lambda s, d: _common(s, d)
ORACLES["common_codes"] = """WITH k AS (SELECT event_id // 100 AS round, user_id % 20 AS worker, CAST((user_id + event_id % 7) % 20 AS INT) AS code FROM events WHERE event_id % 7 < 4)
SELECT round, code FROM k WHERE worker = 3 INTERSECT SELECT round, code FROM k WHERE worker = 5"""


def _common(s, d):
    """Codes that both workers sent in a round, of the messages of a load of four."""
    msgs = detector.as_messages(read(s, d, "events")).where("step < 4")
    return msgs.where("worker = 3").select("round", "code").intersect(msgs.where("worker = 5").select("round", "code"))


QUERIES["latency_measured"] = lambda s, d: latency.measured_units(s, d, TRIALS, WORKERS, SEED).select("trial", "worker", "unit")
ORACLES["latency_measured"] = f"WITH {units_sql()} SELECT trial, worker, unit FROM u"
QUERIES["latency_measured_comm"] = lambda s, d: latency.measured_comm(s, d, TRIALS, 3, WORKERS, SEED)
ORACLES["latency_measured_comm"] = f"WITH {MEASURED}, {comm_sql(TRIALS, 3)} SELECT trial, worker, step, x FROM x"
QUERIES["latency_exp_comm"] = lambda s, d: latency.measured_comm(s, d, TRIALS, 2, WORKERS, SEED, 2000)
ORACLES["latency_exp_comm"] = f"WITH {MEASURED}, {comm_sql(TRIALS, 2, 2000)} SELECT trial, worker, step, x FROM x"
QUERIES["latency_shifted_exp"] = lambda s, d: latency.shifted_exponential(s, 500, 20, fit=fitted_times(s, d, ["worker"])).select("trial", "worker", "unit")
ORACLES["latency_shifted_exp"] = f"WITH {FIT} SELECT t AS trial, worker, shift + CAST(round(round(-ln(({portable_sql('1', 't', 'worker')} + 0.5) / 4503599627370496.0), 9) * excess::DOUBLE) AS BIGINT) AS unit FROM generate_series(0, 499) a(t), fits"
QUERIES["latency_initial_delay"] = lambda s, d: _delayed(s, d)
ORACLES["latency_initial_delay"] = f"WITH {FIT} SELECT t AS trial, worker, CASE WHEN ({portable_sql('1', chr(39) + 'd' + chr(39), 't', 'worker')} + 0.5) / 4503599627370496.0 < 0.3 THEN 8 * (shift + excess) ELSE 0 END AS start FROM generate_series(0, {TRIALS - 1}) a(t), fits"


def _delayed(s, d):
    """Workers that start a round later by eight of their mean computation times."""
    lat = latency.fitted_grid(s, TRIALS, fitted_times(s, d, ["worker"])).withColumn("start", F.lit(0).cast("bigint"))
    return latency.initial_delay(lat, 0.3, 8 * (F.col("shift") + F.col("excess")), SEED).select("trial", "worker", "start")


QUERIES["overlap_arrivals"] = lambda s, d: recover.arrivals(latency.measured_units(s, d, TRIALS, WORKERS, SEED), layout.message_table(s, [_MULTI]), latency.measured_comm(s, d, TRIALS, 4, WORKERS, SEED)).select("trial", "worker", "step", F.col("at").cast("bigint").alias("at"))
#: The recursion itself: each message waits for the one before.
ORACLES["overlap_arrivals"] = f"""WITH RECURSIVE {units_sql()}, {comm_sql(TRIALS, 4)}, y AS (SELECT x.trial, x.worker, step, unit * (step + 1) AS ready, x FROM x JOIN u USING (trial, worker)),
o AS (SELECT trial, worker, step, ready + x AS at_ FROM y WHERE step = 0 UNION ALL SELECT y.trial, y.worker, y.step, greatest(y.ready, o.at_) + y.x FROM o JOIN y ON y.trial = o.trial AND y.worker = o.worker AND y.step = o.step + 1)
SELECT trial, worker, step, CAST(at_ AS BIGINT) AS "at" FROM o"""

_SHORT = scheme("uncoded_multi", 20, 2)
_QUEUE = """WITH RECURSIVE {units}, {msgs}, a AS ({plain}), q AS (SELECT trial, worker, step, at_, row_number() OVER (PARTITION BY trial{by} ORDER BY at_, worker, step, code) AS n{by} FROM a),
o AS (SELECT trial, worker, step, n, at_ + 300 AS out{by2} FROM q WHERE n = 1 UNION ALL SELECT q.trial, q.worker, q.step, q.n, greatest(q.at_, o.out) + 300{by2q} FROM o JOIN q ON q.trial = o.trial AND q.n = o.n + 1{join})
SELECT trial, worker, step, CAST(out AS BIGINT) AS "at" FROM o"""
QUERIES["congested_arrivals"] = lambda s, d: recover.congested(_arr(s, d, _SHORT), 300).select("trial", "worker", "step", F.col("at").cast("bigint").alias("at"))
ORACLES["congested_arrivals"] = _QUEUE.format(units=units_sql(), msgs=messages_sql([_SHORT]), plain=PLAIN, by="", by2="", by2q="", join="")
QUERIES["hierarchy_arrivals"] = lambda s, d: recover.congested(_arr(s, d, _SHORT), 300, groups=4).groupBy("trial").agg(F.max("at").cast("bigint").alias("last"), F.min("at").cast("bigint").alias("first"))
ORACLES["hierarchy_arrivals"] = f"""WITH {units_sql()}, {messages_sql([_SHORT])}, a AS ({PLAIN}),
q AS (SELECT *, 300 * row_number() OVER w AS s, max(at_ - 300 * (rn - 1)) OVER (PARTITION BY trial, worker % 4 ORDER BY rn) AS b FROM (SELECT *, row_number() OVER (PARTITION BY trial, worker % 4 ORDER BY at_, worker, step, code) AS rn FROM a) WINDOW w AS (PARTITION BY trial, worker % 4 ORDER BY at_, worker, step, code)),
h AS (SELECT trial, worker, step, code, s + b AS at_ FROM q), r AS (SELECT *, row_number() OVER (PARTITION BY trial ORDER BY at_, worker, step, code) AS rn FROM h),
e AS (SELECT trial, 300 * rn + max(at_ - 300 * (rn - 1)) OVER (PARTITION BY trial ORDER BY rn) AS at_ FROM r)
SELECT trial, CAST(max(at_) AS BIGINT) AS last, CAST(min(at_) AS BIGINT) AS first FROM e GROUP BY trial"""


def _carry(s, d):
    """Twelve rounds that end with the third of four workers; what is left of a delay holds its worker in the next round."""
    lat = latency.initial_delay(latency.measured_units(s, d, 12, WORKERS, SEED).where("worker < 4"), 0.4, 6000, SEED)
    rows = lat.groupBy(F.lit(0).alias("run")).agg(F.sort_array(F.collect_list(F.struct("trial", "worker", "start", "unit"))).alias("all"))

    def run(pdf):
        import pandas as pd

        cells = sorted((c["trial"], c["worker"], c["start"], c["unit"]) for c in pdf["all"].iloc[0])
        left, out = [0.0] * 4, []
        for t in range(12):
            mine = cells[4 * t : 4 * t + 4]
            start, _ = latency.carry_over(left, [c[2] for c in mine], 0)
            end = sorted(a + c[3] for a, c in zip(start, mine, strict=True))[2]
            left = [max(0.0, a - end) for a in start]
            out.append((t, int(end), int(sum(left))))
        return pd.DataFrame(out, columns=["round", "t", "left_over"])

    return rows.groupBy("run").applyInPandas(run, "round long, t long, left_over long")


QUERIES["carry_over_rounds"] = _carry
ORACLES["carry_over_rounds"] = f"""WITH RECURSIVE {units_sql(12)}, l AS (SELECT trial, list(unit ORDER BY worker) AS unit, list(CASE WHEN ({portable_sql('1', chr(39) + 'd' + chr(39), 'trial', 'worker')} + 0.5) / 4503599627370496.0 < 0.4 THEN 6000 ELSE 0 END ORDER BY worker) AS fresh FROM u WHERE worker < 4 GROUP BY trial),
b AS (SELECT 0 AS round, CAST([0, 0, 0, 0] AS BIGINT[]) AS res, 0::BIGINT AS t UNION ALL
 SELECT b.round + 1, list_transform(range(1, 5), lambda i: greatest(0, b.res[i] + l.fresh[i] - n.t)), n.t FROM b JOIN l ON l.trial = b.round, LATERAL (SELECT CAST(list_sort(list_transform(range(1, 5), lambda i: b.res[i] + l.fresh[i] + l.unit[i]))[3] AS BIGINT) AS t) n)
SELECT CAST(round - 1 AS BIGINT) AS round, t, CAST(list_sum(res) AS BIGINT) AS left_over FROM b WHERE round > 0"""

# Measures --------------------------------------------------------------------------------------


QUERIES["communication_load"] = lambda s, d: done(s, d, list(SCHEMES.values())[:8], steps=4).groupBy("scheme").agg(F.sum("load").alias("load"), F.min("load").alias("least"), F.max("load").alias("most"))
ORACLES["communication_load"] = f"WITH {units_sql()}, {comm_sql(TRIALS, 4)}, {messages_sql(list(SCHEMES.values())[:8])}, {complete_sql(SENT)} SELECT scheme, CAST(sum(load) AS BIGINT) AS load, min(load) AS least, max(load) AS most FROM done GROUP BY scheme"
_FEW = [SCHEMES[n] for n in ("lagrange_single", "lagrange_multi", "uncoded_multi", "uncoded_partial", "gradcode_single")]
QUERIES["average_completion"] = lambda s, d: recover.summarise(done(s, d, _FEW, steps=4), ["scheme"])
ORACLES["average_completion"] = f"WITH {units_sql()}, {comm_sql(TRIALS, 4)}, {messages_sql(_FEW)}, {complete_sql(SENT)} SELECT scheme, CAST(sum(t) // count(*) AS BIGINT) AS avg_t, CAST(sum(load) * 1000 // count(*) AS BIGINT) AS avg_load, count(*) AS trials FROM done GROUP BY scheme"
QUERIES["reduction_vs_baseline"] = lambda s, d: recover.reductions(recover.summarise(done(s, d, _FEW, steps=4).withColumn("r", F.lit(4)), ["scheme", "r"]), "lagrange_single", ["r"])
ORACLES["reduction_vs_baseline"] = f"WITH {units_sql()}, {comm_sql(TRIALS, 4)}, {messages_sql(_FEW)}, {complete_sql(SENT)}, v AS (SELECT scheme, CAST(sum(t) // count(*) AS BIGINT) AS avg_t FROM done GROUP BY scheme) SELECT v.scheme, 4 AS r, v.avg_t, b.avg_t AS base_t, round((b.avg_t - v.avg_t) * 100.0::DOUBLE / b.avg_t, 4) AS reduction FROM v JOIN v b ON b.scheme = 'lagrange_single'"
QUERIES["waste"] = lambda s, d: _waste(s, d)
ORACLES["waste"] = f"WITH {units_sql()}, {messages_sql([_MULTI])}, {complete_sql(PLAIN)}, x1 AS (SELECT u.trial, CAST(sum(least(t // unit, 4)) AS BIGINT) AS executed FROM u JOIN done USING (trial) GROUP BY 1), y1 AS (SELECT trial, count(*) AS useful FROM f JOIN done USING (trial) WHERE at_ <= done.t GROUP BY 1) SELECT trial, executed, useful FROM x1 JOIN y1 USING (trial)"


def _waste(s, d):
    arr = _arr(s, d)
    return recover.waste(arr, recover.complete(arr), latency.measured_units(s, d, TRIALS, WORKERS, SEED), 4).select("trial", "executed", "useful")


QUERIES["traffic"] = lambda s, d: done(s, d, _FEW).groupBy("scheme").agg(F.sum(recover.traffic_bytes(F.col("load"), 64)).alias("bytes"))
ORACLES["traffic"] = f"WITH {units_sql()}, {messages_sql(_FEW)}, {complete_sql(PLAIN)} SELECT scheme, CAST(sum(load * 512) AS BIGINT) AS bytes FROM done GROUP BY scheme"
QUERIES["ecdf_trials"] = lambda s, d: _ecdf(s, d)
ORACLES["ecdf_trials"] = f"WITH {units_sql()}, {messages_sql(_FEW)}, {complete_sql(PLAIN)} SELECT scheme, g * 500 AS at_us, count(*) FILTER (t <= g * 500) AS ended FROM done, generate_series(1, 20) x(g) GROUP BY ALL"


def _ecdf(s, d):
    """Trials ended by each point of a grid: one pass, a conditional count per point."""
    ends = done(s, d, _FEW)
    wide = ends.groupBy("scheme").agg(F.array(*[F.struct(F.lit(500 * g).cast("bigint").alias("at_us"), F.count(F.when(F.col("t") <= 500 * g, 1)).alias("ended")) for g in range(1, 21)]).alias("g"))
    return wide.select("scheme", F.explode("g").alias("g")).select("scheme", "g.*")


# Closed forms ----------------------------------------------------------------------------------

# Parameters are fitted to the measured computation times; grids are in steps of 100 microseconds.
_BINOMIAL = "WITH {fit}, g AS (SELECT k, CASE WHEN k * 100 <= {r} * shift THEN 0.0::DOUBLE ELSE 1 - exp(-(k * 100::DOUBLE / {r} - shift) / excess) END AS p FROM generate_series(0, 199) t(k), fit), b AS (SELECT n, round(gamma({K} + 1) / (gamma(n + 1) * gamma({K} - n + 1))) AS ways FROM generate_series({need}, {K}) t(n)) SELECT k, round(sum(ways * pow(p, n) * pow(1 - p, {K} - n)), 8) AS cdf FROM g, b GROUP BY k"
QUERIES["cdf_worker_threshold"] = lambda s, d: analytic.worker_cdf_table(s, 6, 3, 4, 200, 100, fit=fitted_times(s, d))
ORACLES["cdf_worker_threshold"] = _BINOMIAL.format(fit=FIT, K=6, r=3, need=4)
QUERIES["cdf_lagrange_single"] = lambda s, d: analytic.worker_cdf_table(s, 10, 5, 3, 200, 100, fit=fitted_times(s, d))
ORACLES["cdf_lagrange_single"] = _BINOMIAL.format(fit=FIT, K=10, r=5, need=3)
QUERIES["cdf_message_threshold"] = lambda s, d: analytic.message_cdf_table(s, 6, 3, 11, 100, 100, fit=fitted_times(s, d))
ORACLES["cdf_message_threshold"] = f"""WITH {FIT}, g AS (SELECT k, k * 100::DOUBLE AS t, shift, excess FROM generate_series(0, 99) x(k), fit),
f AS (SELECT k, {", ".join(f"CASE WHEN t <= {i} * shift THEN 0 ELSE 1 - exp(-(t / {i} - shift) / excess) END AS f{i}" for i in (1, 2, 3))} FROM g),
c_ AS (SELECT a, b, c, 6 - a - b - c AS e, round(720 / (gamma(a + 1) * gamma(b + 1) * gamma(c + 1) * gamma(7 - a - b - c))) AS ways FROM generate_series(0, 6) x(a), generate_series(0, 6) y(b), generate_series(0, 6) z(c) WHERE a + b + c <= 6 AND b + 2 * c + 3 * (6 - a - b - c) >= 11)
SELECT k, round(sum(ways * pow(1 - f1, a) * pow(f1 - f2, b) * pow(f2 - f3, c) * pow(f3, e)), 8) AS cdf FROM f, c_ GROUP BY k"""
QUERIES["cdf_layered"] = lambda s, d: analytic.message_cdf_table(s, 6, 3, 8, 100, 100, weight=lambda n: (n >= 2) + (n >= 3), fit=fitted_times(s, d))
ORACLES["cdf_layered"] = ORACLES["cdf_message_threshold"].replace("b + 2 * c + 3 * (6 - a - b - c) >= 11", "c + 2 * (6 - a - b - c) >= 8")


def _closed(s, d):
    """Closed-form means of count-threshold schemes where the shift is a tenth of the mean beyond it, in microseconds at the measured mean time of a computation."""
    cases = [scheme("gradcode_single", 40, 10), scheme("lagrange_single", 40, 10), scheme("lagrange_multi", 40, 10), scheme("lagrange_multi", 40, 10, polys=2), scheme("gradcode_layered", 40, 10, orders=(10, 9, 1), P=4), scheme("lagrange_multi", 6, 3), scheme("lagrange_multi", 10, 5)]
    rows = [(c.label, c.K, c.r, round(analytic.expected_completion(lambda t, c=c: analytic.cdf(c, t), 8.0, 0.002) * 10000)) for c in cases]
    base = s.createDataFrame(rows, "scheme string, K int, r int, base long")  # a computation takes 1,100 on average
    return fitted_times(s, d).crossJoin(F.broadcast(base)).select("scheme", "K", "r", F.expr("base * (shift + excess) div 1100").alias("expected"))


QUERIES["expected_completion"] = lambda s, d: _closed(s, d)
ORACLES["expected_completion"] = f"WITH {FIT} SELECT scheme, K, r, base * (shift + excess) // 1100 AS expected FROM (VALUES ('gradcode_single', 40, 10, 15496), ('lagrange_single', 40, 10, 2897), ('lagrange_multi', 40, 10, 1269), ('lagrange_multi_2', 40, 10, 1507), ('gradcode_layered', 40, 10, 3109), ('lagrange_multi', 6, 3, 1894), ('lagrange_multi', 10, 5, 1474)) t(scheme, K, r, base), fit"
QUERIES["expected_by_integration"] = lambda s, d: analytic.integrate(analytic.worker_cdf_table(s, 6, 3, 4, 2000, 20, fit=fitted_times(s, d)), 20).select(F.round("expected", 2).alias("expected"))
ORACLES["expected_by_integration"] = f"WITH {FIT} SELECT round(3 * (shift + (1/3.0 + 1/4.0 + 1/5.0 + 1/6.0)::DOUBLE * excess), 2)::DOUBLE AS expected FROM fit"
QUERIES["expected_order_statistic"] = lambda s, d: _order_statistics(s, d)
ORACLES["expected_order_statistic"] = f"WITH {FIT} SELECT K, r, need, round(r * (shift + list_sum(list_transform(range(K - need + 1, K + 1), lambda i: 1.0::DOUBLE / i)) * excess), 3) AS expected FROM (VALUES (40, 10, 31), (40, 10, 7), (6, 3, 4), (10, 5, 3)) t(K, r, need), fit"


def _order_statistics(s, d):
    """Mean of the need-th smallest of K workers' times for r computations, at the fitted parameters."""
    cases = [F.struct(F.lit(K).alias("K"), F.lit(r).alias("r"), F.lit(n).alias("need"), F.round(r * (F.col("shift") + analytic.harmonic(K, n) * F.col("excess")), 3).alias("expected")) for K, r, n in ((40, 10, 31), (40, 10, 7), (6, 3, 4), (10, 5, 3))]
    return fitted_times(s, d).select(F.inline(F.array(*cases)))


QUERIES["measurement_counts"] = lambda s, d: measurements(s, d).groupBy("worker", "kind").agg(F.count("*").alias("n"), F.sum("us").alias("us"))
ORACLES["measurement_counts"] = f"WITH {MEASURED} SELECT worker, kind, count(*) AS n, CAST(sum(us) AS BIGINT) AS us FROM m GROUP BY ALL"
