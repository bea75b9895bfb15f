"""Queries over layouts, masks and realizations of stragglers."""

from __future__ import annotations

from pyspark.sql import functions as F

from tolerant_gd.functions.randoms import portable_sql
from tolerant_gd.operators import layout
from tolerant_gd.plans.scheme import messages, recoverable, scheme, worker_threshold

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _slots_sql(K: int, r: int, P: int = 1) -> str:
    z = K // P
    return f"SELECT CAST(w AS INT) AS worker, CAST(j AS INT) AS ord, CAST(w // {z} * {z} + (w % {z} + j) % {z} AS INT) AS batch FROM generate_series(0, {K - 1}) a(w), generate_series(0, {r - 1}) b(j)"


QUERIES["layout_cyclic"] = lambda s, d: layout.cyclic_layout(s, 10, 4)
ORACLES["layout_cyclic"] = _slots_sql(10, 4)
QUERIES["layout_clustered"] = lambda s, d: layout.clustered_layout(s, 40, 6, 4)
ORACLES["layout_clustered"] = _slots_sql(40, 6, 4)
QUERIES["layout_repetition"] = lambda s, d: layout.repetition_layout(s, 40, 10)
ORACLES["layout_repetition"] = _slots_sql(40, 10, 4)
QUERIES["layout_random"] = lambda s, d: layout.random_layout(s, 20, 4, 7)
ORACLES["layout_random"] = f"SELECT worker, CAST(o AS INT) AS ord, batch FROM (SELECT CAST(w AS INT) AS worker, CAST(b AS INT) AS batch, row_number() OVER (PARTITION BY w ORDER BY {portable_sql('7', 'w', 'b')}, b) - 1 AS o FROM generate_series(0, 19) x(w), generate_series(0, 19) y(b)) WHERE o < 4"
QUERIES["layout_layered"] = lambda s, d: layout.layered_layout(s, 6, [3, 2])
ORACLES["layout_layered"] = f"SELECT CAST(layer AS INT) AS layer, worker, ord, batch FROM ({_slots_sql(6, 3)}), (VALUES (0, 3), (1, 2)) l(layer, m) WHERE ord < m"
QUERIES["layout_shared"] = lambda s, d: layout.shared_layout(s, 6, 3, 2)
ORACLES["layout_shared"] = f"SELECT worker, ord AS step, batch AS code, ord + 2 AS needs FROM ({_slots_sql(6, 2)})"
QUERIES["mask_statistics"] = lambda s, d: layout.mask_statistics(layout.cyclic_layout(s, 12, 5))
ORACLES["mask_statistics"] = f"WITH t AS ({_slots_sql(12, 5)}), b AS (SELECT batch, count(*) AS copies, count(DISTINCT worker) AS workers FROM t GROUP BY batch), w AS (SELECT worker, count(*) AS n FROM t GROUP BY worker) SELECT batch, copies, workers, (SELECT min(n) FROM w) AS least_row, (SELECT max(n) FROM w) AS most_row, (SELECT count(*) FROM w) - (SELECT min(copies) FROM b) AS degree FROM b"
QUERIES["region_clusters"] = lambda s, d: layout.region_clusters(s, d)
ORACLES["region_clusters"] = "SELECT n_nationkey AS worker, CAST(dense_rank() OVER (ORDER BY r_regionkey) AS INT) AS cluster, CAST(row_number() OVER (PARTITION BY r_regionkey ORDER BY n_nationkey) - 1 AS INT) AS place, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey"


def _realizations(s):
    """Good subsets of finishers of all 1,024 with one cluster and with two, and whether the first are among the second."""
    bits = s.range(1024).select(F.col("id").alias("bits"))
    plain = F.bit_count("bits") >= 8
    low, high = F.bit_count(F.col("bits").bitwiseAND(31)), F.bit_count(F.shiftright("bits", 5))
    split = (low >= 3) & (high >= 3)
    return bits.agg(F.count(F.when(plain, 1)).alias("unclustered"), F.count(F.when(split, 1)).alias("clustered"), F.count(F.when(plain & ~split, 1)).alias("lost"))


QUERIES["realizations_good"] = lambda s, d: _realizations(s)
ORACLES["realizations_good"] = "SELECT count(*) FILTER (bit_count(b) >= 8) AS unclustered, count(*) FILTER (bit_count(b & 31) >= 3 AND bit_count(b >> 5) >= 3) AS clustered, count(*) FILTER (bit_count(b) >= 8 AND NOT (bit_count(b & 31) >= 3 AND bit_count(b >> 5) >= 3)) AS lost FROM generate_series(0, 1023) t(b)"


def _by_recovery(s, sch):
    """Realizations by number of finishers, from the scheme's real recovery condition."""
    K = sch.K
    good = [b for b in range(1 << K) if recoverable(sch, [w for w in range(K) if b >> w & 1])]
    rows = s.createDataFrame([(b,) for b in good], "bits bigint")
    return rows.groupBy(F.bit_count("bits").cast("int").alias("finished")).agg(F.count("*").alias("good"))


QUERIES["realizations_shared"] = lambda s, d: _by_recovery(s, scheme("gradcode_shared", 6, 3, order=2))
ORACLES["realizations_shared"] = "WITH c AS (SELECT b, count(DISTINCT (w + q) % 6) AS codes FROM generate_series(0, 63) t(b), generate_series(0, 5) u(w), generate_series(0, 1) v(q) WHERE (b >> w) & 1 = 1 GROUP BY b) SELECT CAST(bit_count(b) AS INT) AS finished, count(*) AS good FROM c WHERE codes >= 5 GROUP BY 1"
QUERIES["realizations_repetition"] = lambda s, d: _by_recovery(s, scheme("gradcode_repeat", 12, 3))
ORACLES["realizations_repetition"] = "SELECT CAST(bit_count(b) AS INT) AS finished, count(*) AS good FROM generate_series(0, 4095) t(b) WHERE b & 7 > 0 AND (b >> 3) & 7 > 0 AND (b >> 6) & 7 > 0 AND (b >> 9) & 7 > 0 GROUP BY 1"


def _thresholds(s):
    """Worked cases: messages and workers that suffice."""
    from tolerant_gd.plans.scheme import message_threshold

    cases = [
        ("cyclic", scheme("gradcode_single", 6, 3)),
        ("shared", scheme("gradcode_shared", 6, 3, order=2)),
        ("layered", scheme("gradcode_layered", 6, 3, orders=(3, 2))),
        ("repetition", scheme("gradcode_repeat", 40, 10)),
        ("clustered", scheme("gradcode_single", 10, 3, P=2)),
        ("unclustered", scheme("gradcode_single", 10, 3)),
        ("lagrange_single", scheme("lagrange_single", 6, 3)),
        ("lagrange_multi", scheme("lagrange_multi", 6, 3)),
        ("lagrange_padded", scheme("lagrange_single", 20, 3)),
        ("two_polynomials", scheme("lagrange_multi", 40, 10, polys=2)),
        ("partial", scheme("uncoded_partial", 40, 2, tolerance=0.05)),
    ]
    rows = [(n, message_threshold(c), len([m for m in messages(c) if m.first])) for n, c in cases]
    return s.createDataFrame(rows, "case string, threshold int, messages int")


QUERIES["thresholds"] = lambda s, d: _thresholds(s)
ORACLES["thresholds"] = "SELECT * FROM (VALUES ('cyclic', 4, 6), ('shared', 5, 12), ('layered', 8, 12), ('repetition', 1, 40), ('clustered', 3, 10), ('unclustered', 8, 10), ('lagrange_single', 3, 6), ('lagrange_multi', 11, 18), ('lagrange_padded', 13, 20), ('two_polynomials', 39, 200), ('partial', 38, 80)) t(\"case\", threshold, messages)"


def _worker_thresholds(s):
    cases = []
    for K, r, P in ((6, 3, 2), (20, 4, 4), (40, 10, 4)):
        cases += [scheme("gradcode_single", K, r), scheme("gradcode_single", K, r, P=P), scheme("gradcode_shared", K, r, order=2), scheme("gradcode_shared", K, r, P=P, order=r - 1), scheme("lagrange_single", K, r), scheme("lagrange_multi", K, r)]
        cases += [scheme("uncoded_multi", K, r), scheme("uncoded_partial", K, r, tolerance=0.1), scheme("uncoded_single", K, r), scheme("wait_all", K), scheme("first_workers", K, need=K - 5), scheme("backup_workers", K, extra=2)]
    cases += [scheme("gradcode_repeat", 6, 3), scheme("gradcode_repeat", 20, 4), scheme("gradcode_repeat", 40, 10)]
    return s.createDataFrame([(c.label, c.K, c.r, c.P, worker_threshold(c)) for c in cases], "scheme string, K int, r int, P int, workers int")


QUERIES["worker_thresholds"] = lambda s, d: _worker_thresholds(s)
#: Whatever r - 1 workers of the cyclic layouts are missing, each batch is still held; message counts give the others.
ORACLES["worker_thresholds"] = """WITH c(K, r, P) AS (VALUES (6, 3, 2), (20, 4, 4), (40, 10, 4)),
w AS (SELECT *, unnest([{'scheme': 'gradcode_single', 'r': r, 'P': 1, 'n': K - r + 1}, {'scheme': 'gradcode_single', 'r': r, 'P': P, 'n': K - r + 1}, {'scheme': 'gradcode_shared', 'r': r, 'P': 1, 'n': K - r + 1},
  {'scheme': 'gradcode_shared', 'r': r, 'P': P, 'n': K - r + 1}, {'scheme': 'lagrange_single', 'r': r, 'P': 1, 'n': 2 * ((K + r - 1) // r) - 1}, {'scheme': 'lagrange_multi', 'r': r, 'P': 1, 'n': (2 * K - 1 + r - 1) // r},
  {'scheme': 'uncoded_multi', 'r': r, 'P': 1, 'n': K - r + 1}, {'scheme': 'uncoded_partial', 'r': r, 'P': 1, 'n': K - K // 10 - r + 1}, {'scheme': 'uncoded_single', 'r': r, 'P': 1, 'n': K - r + 1}, {'scheme': 'wait_all', 'r': 1, 'P': 1, 'n': K},
  {'scheme': 'first_workers', 'r': 1, 'P': 1, 'n': K - 5}, {'scheme': 'backup_workers', 'r': 1, 'P': 1, 'n': K + 2}, {'scheme': 'gradcode_repeat', 'r': r, 'P': K // r, 'n': K - r + 1}], recursive := true) FROM c)
SELECT scheme, K, r_1 AS r, P_1 AS P, CAST(n AS INT) AS workers FROM w"""
