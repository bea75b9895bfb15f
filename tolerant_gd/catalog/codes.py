"""Queries that encode, lose and decode gradients, exactly."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import functions as F

from tolerant_gd.catalog.gradients import SAMPLE, THETA, Z, long_sum
from tolerant_gd.operators import lagrange, polycode, regress
from tolerant_gd.plans.scheme import decode_ops, message_threshold, messages, scheme, slots
from tolerant_gd.sources.tables import exact_sample, read
from tolerant_gd.streaming import detector

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _grads(s, d, K: int):
    return regress.partial_gradients(exact_sample(s, d, K), THETA)


def _decode_every(s, d, masks, received_sets, K: int):
    """Decode from each received set; one row a set and dimension."""
    h = polycode.degree(masks, set().union(*masks))
    points = list(range(1, len(masks) + 1))
    codes = polycode.encode(_grads(s, d, K), polycode.encode_coefs(masks, points))
    sets = [(i, *polycode.decode_coefs(points, list(r), h)) for i, r in enumerate(received_sets)]
    return polycode.decode(codes, sets)


def _direct_sql(K: int, sets: int) -> str:
    return f"SELECT CAST(i AS INT) AS set_id, dim, v FROM ({long_sum(f'({Z} - y)', '', SAMPLE.format(K=K))}), generate_series(0, {sets - 1}) t(i)"


CYCLIC = polycode.supports(slots(scheme("gradcode_single", 6, 3)))
SHARED = polycode.supports([(w, j, (w + j) % 6) for w in range(6) for j in range(2)])
LAYERED = polycode.supports(slots(scheme("gradcode_layered", 6, 3, orders=(3, 2))), [(w, m) for w in range(6) for m in (2, 3)])

QUERIES["encode_cyclic"] = lambda s, d: polycode.encode(_grads(s, d, 6), polycode.encode_coefs(CYCLIC)).select("code", "dim", F.col("c").cast("bigint").alias("c"))


def _encode_sql() -> str:
    """Coefficients from the definition: the product over codes that lack the batch."""
    return f"""WITH g AS ({long_sum(f'({Z} - y)', 'batch', SAMPLE.format(K=6))}), m AS (SELECT i, (i + j) % 6 AS b FROM generate_series(0, 5) a(i), generate_series(0, 2) c(j)),
c AS (SELECT m.i, m.b, CAST(list_product(list_transform([z FOR z IN range(0, 6) IF (m.b - z + 6) % 6 > 2], lambda z: m.i - z)) AS BIGINT) AS x FROM m)
SELECT CAST(i AS INT) AS code, dim, CAST(sum(x * v) AS BIGINT) AS c FROM g JOIN c ON g.batch = c.b GROUP BY i, dim"""


ORACLES["encode_cyclic"] = _encode_sql()
QUERIES["decode_cyclic_all_sets"] = lambda s, d: _decode_every(s, d, CYCLIC, combinations(range(6), 4), 6)
ORACLES["decode_cyclic_all_sets"] = _direct_sql(6, 15)
QUERIES["decode_shared_example"] = lambda s, d: _decode_every(s, d, SHARED, combinations(range(6), 5), 6)
ORACLES["decode_shared_example"] = _direct_sql(6, 6)
QUERIES["decode_layered_example"] = lambda s, d: _decode_every(s, d, LAYERED, combinations(range(12), 8), 6)
ORACLES["decode_layered_example"] = _direct_sql(6, 495)


def _decode_clustered(s, d):
    """Two clusters of five, r = 3: every pair of three-worker sets; each cluster decodes its own share."""
    grads = _grads(s, d, 10)
    masks = polycode.supports([(w, j, (w + j) % 5) for w in range(5) for j in range(3)])
    points, out = list(range(1, 6)), None
    for c in (0, 1):
        own = grads.where(F.expr(f"batch div 5 = {c}")).withColumn("batch", F.col("batch") % 5)
        codes = polycode.encode(own, polycode.encode_coefs(masks, points))
        sets = [(i, *polycode.decode_coefs(points, list(r), 2)) for i, r in enumerate(combinations(range(5), 3))]
        one = polycode.decode(codes, sets)
        out = one if out is None else out.union(one)
    return out.groupBy("set_id", "dim").agg(F.sum("v").alias("v"))


QUERIES["decode_clustered"] = _decode_clustered
ORACLES["decode_clustered"] = _direct_sql(10, 10)


def _decode_padded(s, d):
    """Uneven columns: the first worker lacks one of its slots; lighter polynomials get unused roots."""
    masks = [set(m) for m in CYCLIC]
    masks[0] = masks[0] - {2}
    h = polycode.degree(masks, set(range(6)))
    points = list(range(1, 7))
    codes = polycode.encode(_grads(s, d, 6), polycode.encode_coefs(masks, points, pad=True))
    return polycode.decode(codes, [(i, *polycode.decode_coefs(points, list(r), h)) for i, r in enumerate(combinations(range(6), h + 1))])


QUERIES["decode_uneven_columns"] = _decode_padded
ORACLES["decode_uneven_columns"] = _direct_sql(6, 6)


def _decode_hybrid(s, d):
    """K = r = 5: one finished worker's plain average, against the layered decoding and the direct sum."""
    grads = _grads(s, d, 5)
    sch = scheme("gradcode_hybrid", 5, 5, orders=(5, 3))
    masks = polycode.supports(slots(sch), [(w, m) for w in range(5) for m in (3, 5)])
    h = polycode.degree(masks, set(range(5)))
    layered = polycode.decode(polycode.encode(grads, polycode.encode_coefs(masks)), [(0, *polycode.decode_coefs(list(range(1, 11)), list(range(h + 1)), h))])
    plain = grads.groupBy("dim").agg(F.sum("v").alias("v")).select(F.lit(1).alias("set_id"), "dim", F.col("v").cast("bigint").alias("v"))
    return layered.union(plain)


QUERIES["decode_hybrid"] = _decode_hybrid
ORACLES["decode_hybrid"] = _direct_sql(5, 2)


def _conditioning(s, d):
    """How much decoding may amplify float error on the gradients of lineitem, worst of all received sets, for the integer points."""
    rows = []
    for K, r in ((6, 3), (8, 4), (10, 5)):
        masks = polycode.supports([(w, j, (w + j) % K) for w in range(K) for j in range(r)])
        grads: dict[int, dict[int, int]] = {}
        for g in _grads(s, d, K).collect():  # K times 5 numbers
            grads.setdefault(g.dim, {})[g.batch] = int(g.v)
        worst = max(polycode.growth(masks, list(c), grads) for c in combinations(range(K), K - r + 1))
        rows.append((K, r, float(f"{worst:.6g}")))
    return s.createDataFrame(rows, "K int, r int, growth double")


QUERIES["decode_conditioning"] = lambda s, d: _conditioning(s, d)


# Lagrange codes ------------------------------------------------------------------------------


XS = ["x0", "x1", "x2", "x3", "x4"]


ALIGNED = ["l_orderkey", "x4", "y", "x1", "x2", "x3"]


def _rows(s, d, K: int):
    """Aligned blocks of lineitem."""
    return regress.align_blocks(exact_sample(s, d, K), ALIGNED)


def _lagrange(s, d, K: int, r: int, polys: int, received=None):
    code = lagrange.Code(K, r, polys)
    coded = lagrange.encode(_rows(s, d, K), code, XS)
    total = K * code.draws
    received = received or sorted(range(total), key=lambda i: (i * 7919) % total)[: code.threshold]
    return lagrange.decode(lagrange.work(coded, list(THETA), XS), code, received)


#: (K, r, polys)
_CODES = {"single": (6, 3, 3), "multi": (6, 3, 1), "two_polys": (6, 4, 2), "padded": (7, 3, 3)}
for _name, _c in _CODES.items():
    QUERIES[f"lagrange_decode_{_name}"] = lambda s, d, c=_c: _lagrange(s, d, *c)
    ORACLES[f"lagrange_decode_{_name}"] = long_sum(Z, "")


def _encode_rows(s, d):
    """Checksums of coded rows: field sums of the first three features of every message."""
    coded = lagrange.encode(_rows(s, d, 6), lagrange.Code(6, 2, 2), XS)
    return coded.groupBy("message", "grp").agg(*[F.sum(F.col(x).cast("decimal(38,0)")).cast("decimal(38,0)").cast("string").alias(x) for x in XS[:3]])


def _encode_rows_sql() -> str:
    p = lagrange.PRIME
    code = lagrange.Code(6, 2, 2)
    values = ", ".join(f"({w * code.draws + u}, {b}, {c}::HUGEINT)" for w, u, cs in code.encode_coefs() for b, c in enumerate(cs))
    cols = ", ".join(f"CAST(sum({x}) AS VARCHAR) AS {x}" for x in XS[:3])
    inner = ", ".join(f"sum({x}::HUGEINT * c % {p}) % {p} AS {x}" for x in XS[:3])
    return f"""WITH s AS (SELECT *, row_number() OVER (PARTITION BY batch ORDER BY l_orderkey, x4, y, x1, x2, x3) - 1 AS pos FROM ({SAMPLE.format(K=6)})),
c(message, b, c) AS (VALUES {values}), e AS (SELECT message, batch // 3 AS grp, pos, {inner} FROM s JOIN c ON batch % 3 = b GROUP BY ALL)
SELECT CAST(message AS INT) AS message, CAST(grp AS INT) AS grp, {cols} FROM e GROUP BY message, grp"""


QUERIES["lagrange_encode_rows"] = _encode_rows
ORACLES["lagrange_encode_rows"] = _encode_rows_sql()


def _mds(s, d):
    """X'X theta from any three of five coded copies of three row groups of the Gram matrix."""
    g = regress.gram(exact_sample(s, d, 20))
    full = g.where("j >= 0").select("i", "j", "v").union(g.where("j > i").select(F.col("j").alias("i"), F.col("i").alias("j"), "v"))
    theta = F.array(*[F.lit(t) for t in THETA])
    product = full.groupBy("i").agg(F.sum((F.col("v") * F.get(theta, F.col("j"))).cast("decimal(38,0)")).alias("p"))
    groups = product.select((F.col("i") % 3).alias("g"), F.expr("i div 3").alias("place"), "p")
    weights = lagrange.mds_gram(5, 3, 3)
    coefs = s.createDataFrame([(k, g_, w) for k, row in enumerate(weights) for g_, w in enumerate(row)], "k int, g int, w bigint")
    coded = groups.join(F.broadcast(coefs), "g").groupBy("k", "place").agg(F.sum((F.col("p") * F.col("w")).cast("decimal(38,0)")).alias("c"))
    rows, divisor = lagrange.mds_decode(5, 3, [4, 1, 2])
    back = s.createDataFrame([(k, g_, rows[g_][j]) for g_ in range(3) for j, k in enumerate([4, 1, 2])], "k int, g int, w bigint")
    out = coded.join(F.broadcast(back), "k").groupBy("g", "place").agg(F.sum((F.col("c") * F.col("w")).cast("decimal(38,0)")).alias("v"))
    return out.select((F.col("g") + 3 * F.col("place")).cast("int").alias("dim"), F.expr(f"v div {divisor}").cast("bigint").alias("v")).where("dim < 5")


QUERIES["mds_gram_decode"] = _mds
ORACLES["mds_gram_decode"] = long_sum(Z, "")


def _operations(s, d):
    """Operations (100 dims) and messages to decode all rounds of the events whose messages reach the threshold."""
    schemes = [scheme("wait_all", 40), scheme("uncoded_multi", 40, 10), scheme("gradcode_single", 40, 10), scheme("lagrange_single", 40, 10), scheme("lagrange_multi", 40, 10), scheme("lagrange_multi", 40, 10, polys=2)]
    rows = [(c.label, message_threshold(c), decode_ops(c, 100)["combine"], decode_ops(c, 100)["weights"], len([m for m in messages(c) if m.first])) for c in schemes]
    each = s.createDataFrame(rows, "scheme string, threshold int, combine int, weights int, messages int")
    loads = detector.as_messages(read(s, d, "events")).groupBy("round").agg(F.count("*").alias("load")).groupBy("load").agg(F.count("*").alias("n"))
    rounds = F.sum(F.when(F.col("load") >= F.col("threshold"), F.col("n")).otherwise(0))
    summed = loads.crossJoin(F.broadcast(each)).groupBy(*each.columns).agg(rounds.alias("rounds"))
    return summed.select("scheme", "threshold", "rounds", *[(F.col(c) * F.col("rounds")).alias(c) for c in ("combine", "weights", "messages")])


QUERIES["decoding_operations"] = lambda s, d: _operations(s, d)
ORACLES["decoding_operations"] = "SELECT scheme, threshold, rounds, combine * rounds AS combine, weights * rounds AS weights, messages * rounds AS messages FROM (SELECT t.*, count(*) FILTER (load >= threshold) AS rounds FROM (VALUES ('wait_all', 40, 4000, 0, 40), ('uncoded_multi', 40, 4000, 0, 400), ('gradcode_single', 31, 3100, 961, 40), ('lagrange_single', 7, 700, 77, 40), ('lagrange_multi', 79, 7900, 9401, 400), ('lagrange_multi_2', 39, 3900, 2301, 200)) t(scheme, threshold, combine, weights, messages), (SELECT count(*) AS load FROM events GROUP BY event_id // 100) GROUP BY ALL)"


def _residuals(s, d):
    """Relative error of float decoding for small K (exact decoding is used beyond), over all of lineitem."""
    rows, grams = [], {}
    for K, r, v in ((6, 3, 3), (6, 4, 2), (8, 4, 4), (12, 4, 4)):
        if K not in grams:
            grams[K] = lagrange.cross_grams(_rows(s, d, K), XS, K)
        code = lagrange.Code(K, r, v, exact=False)
        rows.append((K, r, v, lagrange.gram_residual(grams[K], THETA, code, list(range(code.threshold))) < 1e-3))
    return s.createDataFrame(rows, "K int, r int, polys int, fine boolean")


QUERIES["decode_residual"] = _residuals
ORACLES["decode_residual"] = "SELECT * FROM (VALUES (6, 3, 3, true), (6, 4, 2, true), (8, 4, 4, true), (12, 4, 4, true)) t(K, r, polys, fine)"
