"""Queries over losses, gradients, Gram form, splits and descent."""

from __future__ import annotations

from pyspark.sql import functions as F

from tolerant_gd.operators import regress, train
from tolerant_gd.plans.scheme import scheme
from tolerant_gd.sources.tables import exact_sample, materialise, read, vector_sample

THETA = (1000, 2000, -300, 50, 7)
QUERIES: dict = {}
ORACLES: dict[str, str] = {}

#: Integer sample in SQL; {K} batches.
SAMPLE = "SELECT l_orderkey, l_linenumber, CAST(l_orderkey % {K} AS INT) AS batch, 1 AS x0, CAST(round(l_quantity) AS BIGINT) AS x1, CAST(round(l_discount * 100) AS BIGINT) AS x2, CAST(round(l_tax * 100) AS BIGINT) AS x3, CAST(l_linenumber AS BIGINT) AS x4, CAST(round(l_extendedprice * 100) AS BIGINT) AS y FROM lineitem"
Z = "(1000 * x0 + 2000 * x1 - 300 * x2 + 50 * x3 + 7 * x4)"
DIMS = ", ".join(f"({i}, x{i})" for i in range(5))


def long_sum(value: str, by: str = "batch", sample: str = "") -> str:
    """SQL: sums of x_i * value per group, in long form."""
    sums = ", ".join(f"sum(x{i} * {value}) AS g{i}" for i in range(5))
    group = f"{by}, " if by else ""
    inner = f"SELECT {group}{sums} FROM s" + (f" GROUP BY {by}" if by else "")
    return f"WITH s AS ({sample or SAMPLE.format(K=20)}), w AS ({inner}) " + " UNION ALL ".join(f"SELECT {group}{i} AS dim, CAST(g{i} AS BIGINT) AS v FROM w" for i in range(5))


def _big(df, *keys):
    return df.select(*keys, F.col("v").cast("bigint").alias("v"))


QUERIES["loss_linear"] = lambda s, d: _loss(exact_sample(s, d, 20))
ORACLES["loss_linear"] = f"SELECT batch, CAST(sum(({Z} - y) * ({Z} - y)) AS BIGINT) AS twice_loss FROM ({SAMPLE.format(K=20)}) GROUP BY batch"
QUERIES["loss_linear_mean"] = lambda s, d: regress.loss(exact_sample(s, d, 20), THETA).select(F.round(F.col("loss") / 1e9, 3).alias("loss_e9"))
ORACLES["loss_linear_mean"] = f"SELECT round(avg(CAST(({Z} - y) AS DOUBLE) * ({Z} - y) / 2) / 1e9, 3) AS loss_e9 FROM ({SAMPLE.format(K=20)})"

QUERIES["full_gradient_linear"] = lambda s, d: _big(regress.full_gradient(exact_sample(s, d, 20), THETA), "dim")
ORACLES["full_gradient_linear"] = long_sum(f"({Z} - y)", "")
QUERIES["partial_gradients"] = lambda s, d: _big(regress.partial_gradients(exact_sample(s, d, 20), THETA), "batch", "dim")
ORACLES["partial_gradients"] = long_sum(f"({Z} - y)")
QUERIES["gradient_from_batch_means"] = lambda s, d: _batch_means(s, d)
ORACLES["gradient_from_batch_means"] = f"WITH s AS ({SAMPLE.format(K=20)}), b AS (SELECT batch, count(*) AS n, avg(CAST(x1 * ({Z} - y) AS DOUBLE)) AS m FROM s GROUP BY batch) SELECT CAST(count(*) AS BIGINT) AS batches, round(sum(n * m) / sum(n) / 1e6, 3) AS mean_e6 FROM b"


def _loss(sample):
    """Twice the loss of every batch, exact: bigint as long as every sum is one, decimal(38,0) beyond."""
    sums = sample.groupBy("batch").agg(F.sum(F.expr(f"cast(({Z} - y) * ({Z} - y) as decimal(28,0))")).cast("decimal(38,0)").alias("twice_loss"))
    sums = materialise(sums, "batch-losses")
    beyond = sums.where(F.col("twice_loss") > (1 << 63) - 1)
    return sums if not beyond.isEmpty() else sums.withColumn("twice_loss", F.col("twice_loss").cast("bigint"))


def _batch_means(s, d):
    """The full mean from batch means and sizes (batches by hash differ in size, so sizes carry along)."""
    sample = exact_sample(s, d, 20)
    g = regress.partial_gradients(sample, THETA).where("dim = 1").join(F.broadcast(regress.batch_sizes(sample)), "batch")
    mean = g.withColumn("m", F.col("v").cast("double") / F.col("n"))
    return mean.agg(F.count("*").alias("batches"), F.round(F.sum(F.col("n") * F.col("m")) / F.sum("n") / 1e6, 3).alias("mean_e6"))


QUERIES["gram_matrix"] = lambda s, d: _big(regress.gram(exact_sample(s, d, 20)), "i", "j")
ORACLES["gram_matrix"] = f"WITH s AS ({SAMPLE.format(K=20)}) " + " UNION ALL ".join(
    [f"SELECT {i} AS i, {j} AS j, CAST(sum(x{i} * x{j}) AS BIGINT) AS v FROM s" for i in range(5) for j in range(i, 5)] + [f"SELECT {i}, -1, CAST(sum(x{i} * y) AS BIGINT) FROM s" for i in range(5)]
)
QUERIES["gram_gradient"] = lambda s, d: _big(regress.gram_gradient(regress.gram(exact_sample(s, d, 20)), THETA), "dim")
ORACLES["gram_gradient"] = long_sum(f"({Z} - y)", "")
QUERIES["gram_embeddings"] = lambda s, d: regress.gram_vectors(vector_sample(s, d, 20), 64).where("j >= 0").groupBy("i", "j").agg(F.round(F.sum("v"), 5).alias("v"))
ORACLES["gram_embeddings"] = "WITH e AS (SELECT vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) - 1 AS k FROM embeddings) SELECT CAST(a.k AS INT) AS i, CAST(b.k AS INT) AS j, round(sum(a.v * b.v), 5) AS v FROM e a JOIN e b ON a.vec_id = b.vec_id AND a.k <= b.k GROUP BY ALL"
QUERIES["block_sum_identity"] = lambda s, d: _big(regress.block_products(exact_sample(s, d, 20), THETA).groupBy("dim").agg(F.sum("v").alias("v")), "dim")
ORACLES["block_sum_identity"] = long_sum(Z, "")

QUERIES["batch_split_hash"] = lambda s, d: read(s, d, "orders").groupBy(F.pmod("o_orderkey", F.lit(40)).cast("int").alias("batch")).agg(F.count("*").alias("n"))
ORACLES["batch_split_hash"] = "SELECT CAST(o_orderkey % 40 AS INT) AS batch, count(*) AS n FROM orders GROUP BY 1"
QUERIES["batch_split_balanced"] = lambda s, d: regress.split_balanced(read(s, d, "orders").select("o_orderkey"), 40, ["o_orderkey"]).groupBy("batch").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("first_key"), F.max("o_orderkey").alias("last_key"))
ORACLES["batch_split_balanced"] = "SELECT CAST(batch AS INT) AS batch, count(*) AS n, min(o_orderkey) AS first_key, max(o_orderkey) AS last_key FROM (SELECT o_orderkey, ntile(40) OVER (ORDER BY o_orderkey) - 1 AS batch FROM orders) GROUP BY 1"
QUERIES["batch_split_contiguous"] = lambda s, d: read(s, d, "orders").select(F.expr("o_orderkey div 1000").alias("batch"), "o_orderkey").groupBy("batch").agg(F.count("*").alias("n"))
ORACLES["batch_split_contiguous"] = "SELECT o_orderkey // 1000 AS batch, count(*) AS n FROM orders GROUP BY 1"
QUERIES["pad_blocks"] = lambda s, d: regress.pad_blocks(exact_sample(s, d, 7), ["l_orderkey", "x4", "y", "x1", "x2", "x3"]).groupBy("batch").agg(F.count("*").alias("n"), F.sum(F.expr("pos * x1")).alias("placed"), F.sum("y").alias("y"))
ORACLES["pad_blocks"] = f"WITH s AS (SELECT *, row_number() OVER (PARTITION BY batch ORDER BY l_orderkey, x4, y, x1, x2, x3) - 1 AS pos FROM ({SAMPLE.format(K=7)})) SELECT batch, (SELECT max(pos) + 1 FROM s) AS n, CAST(sum(pos * x1) AS BIGINT) AS placed, CAST(sum(y) AS BIGINT) AS y FROM s GROUP BY batch"

_STEP = "x.dim AS dim, CAST(1000 * [1000, 2000, -300, 50, 7][x.dim + 1] AS BIGINT) - CAST(v AS BIGINT) AS next_theta"
QUERIES["gd_step_exact"] = lambda s, d: regress.full_gradient(exact_sample(s, d, 20), THETA).select("dim", (1000 * F.get(F.array(*[F.lit(t) for t in THETA]), F.col("dim")).cast("bigint") - F.col("v").cast("bigint")).alias("next_theta"))
ORACLES["gd_step_exact"] = f"SELECT {_STEP} FROM ({long_sum(f'({Z} - y)', '')}) x"


def _gd_rounds(s, d):
    """Three rounds on (1, quantity/50): theta in millionths, the Gram form replayed on the driver from d * d numbers."""
    sample = exact_sample(s, d, 20).select("batch", "x0", "x1", "y")
    history = train.descend(sample, rounds=3, eta=1e-4, scale=(1.0, 0.02, 1e-7))
    return s.createDataFrame([(t, i, round(float(v), 6)) for t, theta in enumerate(history) for i, v in enumerate(theta)], "round int, dim int, theta double")


QUERIES["gd_rounds_linear"] = lambda s, d: _gd_rounds(s, d)
ORACLES["gd_rounds_linear"] = """WITH RECURSIVE s AS (SELECT 1.0::DOUBLE AS x0, round(l_quantity) * 0.02::DOUBLE AS x1, round(l_extendedprice * 100) * 1e-7::DOUBLE AS y FROM lineitem),
m AS (SELECT sum(x0 * x0) AS a, sum(x0 * x1) AS b, sum(x1 * x1) AS c, sum(x0 * y) AS p, sum(x1 * y) AS q, count(*) AS n FROM s),
t AS (SELECT 0 AS round, 0.0::DOUBLE AS t0, 0.0::DOUBLE AS t1 UNION ALL
      SELECT round + 1, t0 - 1e-4::DOUBLE * 1000 * ((a * t0 + b * t1 - p) / n), t1 - 1e-4::DOUBLE * 1000 * ((b * t0 + c * t1 - q) / n) FROM t, m WHERE round < 3)
SELECT round, 0 AS dim, round(t0, 6) AS theta FROM t UNION ALL SELECT round, 1, round(t1, 6) FROM t"""


def quality_sample(s, d):
    """Documents with a quality label: x = (1, log(1 + characters), one indicator a language), y = quality."""
    docs = read(s, d, "documents").select("doc_id", "lang", "n_chars")
    rows = docs.join(F.broadcast(read(s, d, "labels").select("doc_id", "quality")), "doc_id")
    x = F.array(F.lit(1.0), F.log1p("n_chars"), *[(F.col("lang") == v).cast("double") for v in ("de", "es", "fr")])
    return rows.select(F.col("doc_id").alias("id"), F.pmod("doc_id", F.lit(10)).cast("int").alias("batch"), x.alias("x"), F.col("quality").cast("double").alias("y"))


_LOGIT = "(0.5 + 0.1 * ln(1 + n_chars) - 0.2 * (lang = 'de')::INT + 0.3 * (lang = 'es')::INT - 0.1 * (lang = 'fr')::INT)"
_LTHETA = (0.5, 0.1, -0.2, 0.3, -0.1)
QUERIES["loss_logistic_quality"] = lambda s, d: regress.loss(quality_sample(s, d), _LTHETA, "logistic").select(F.round("loss", 6).alias("loss"))
ORACLES["loss_logistic_quality"] = f"SELECT round(avg(ln(1 + exp(-(2 * quality - 1) * {_LOGIT}))), 6) AS loss FROM documents JOIN labels USING (doc_id)"
QUERIES["gradient_logistic_quality"] = lambda s, d: regress.partial_gradients(quality_sample(s, d), _LTHETA, "logistic").select("batch", "dim", F.round("v", 6).alias("v"))
ORACLES["gradient_logistic_quality"] = f"""WITH r AS (SELECT CAST(doc_id % 10 AS INT) AS batch, 1 / (1 + exp(-{_LOGIT})) - quality AS p, [1.0, ln(1 + n_chars), (lang = 'de')::INT, (lang = 'es')::INT, (lang = 'fr')::INT]::DOUBLE[] AS x FROM documents JOIN labels USING (doc_id))
SELECT batch, CAST(i AS INT) AS dim, round(sum(p * x[i + 1]), 6) + 0.0 AS v FROM r, generate_series(0, 4) g(i) GROUP BY batch, i"""


def _invariance(s, d):
    """The same parameters, to nine digits, whichever full-recovery scheme carries the gradients."""
    sample = exact_sample(s, d, 6).select("batch", "x0", "x1", "y")
    rows = []
    for sch in (scheme("wait_all", 6), scheme("gradcode_single", 6, 3), scheme("gradcode_shared", 6, 3, order=2), scheme("gradcode_layered", 6, 3, orders=(3, 2)), scheme("lagrange_multi", 6, 3), scheme("uncoded_multi", 6, 3)):
        theta = train.coded_descend(sample, sch, rounds=3, eta=1e-4, scale=(1.0, 0.02, 1e-7))[-1]
        rows += [(sch.label, i, round(float(v), 6)) for i, v in enumerate(theta)]
    return s.createDataFrame(rows, "scheme string, dim int, theta double")


QUERIES["gd_scheme_invariance"] = lambda s, d: _invariance(s, d)
ORACLES["gd_scheme_invariance"] = "WITH g AS (" + ORACLES["gd_rounds_linear"] + ") SELECT n.scheme, dim, theta FROM g, (VALUES ('wait_all'), ('gradcode_single'), ('gradcode_shared'), ('gradcode_layered'), ('lagrange_multi'), ('uncoded_multi')) AS n(scheme) WHERE round = 3"


_TRACED = (scheme("wait_all", 20), scheme("lagrange_multi", 20, 4), scheme("uncoded_partial", 20, 4, tolerance=0.05))


def _training(s, d, rounds: int = 1_000, schemes=_TRACED):
    """Loss against the simulated clock on the embeddings in thousandths (rounds on Gram forms, decoded messages)."""
    sample = vector_sample(s, d, 20)
    whole = [F.round(F.get("x", F.lit(i)) * 1000).cast("bigint").alias(f"x{i}") for i in range(64)]
    wide, rows = sample.select("batch", *whole, F.col("y").cast("bigint").alias("y")), []
    grams = train.batch_grams(sample.withColumn("x", F.transform("x", lambda v: F.round(v * 1000) / 1000)), 64)
    for sch in schemes:
        rows += [(sch.label, *r) for r in train.train(wide, sch, rounds, eta=0.5, scale=(1e-3,) * 64 + (1.0,), grams=grams)]
    return s.createDataFrame(rows, "scheme string, round int, clock double, load int, loss double")


QUERIES["w13_training_trace"] = lambda s, d: _training(s, d)
