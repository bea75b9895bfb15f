"""Every query against its SQL on the smallest tables, and behaviour that SQL does not state."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from tolerant_gd import catalog
from tolerant_gd.operators import recover, regress, relops, train
from tolerant_gd.plans.scheme import scheme
from tolerant_gd.sources.tables import SCHEMAS, exact_sample

HEAVY = {"w4_scenario1", "w5_scenario2_r4", "w6_scenario2_r6", "w7_link_speed", "w4_to_w6_claims", "w12_claims"}
QUERIES, ORACLES = catalog.queries(), catalog.oracle_sql()
#: Claims hold for the measurements of the larger tables; the smallest have too few a worker.
LARGER_ONLY = {n for n in QUERIES if n.endswith("_claims")}


def plain(row):
    return tuple(str(float(v)) if type(v).__name__ in ("float", "Decimal", "int") and not isinstance(v, bool) else str(v) for v in row)


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in SCHEMAS:
        c.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(n for n in ORACLES if n not in HEAVY | LARGER_ONLY))
def test_query_equals_sql(spark, con, sf, name):
    df = QUERIES[name](spark, sf)
    got = con.execute(ORACLES[name])
    names = [d[0] for d in got.description]
    assert sorted(df.columns) == sorted(names)
    want = sorted(plain(r) for r in got.fetchall())
    have = sorted(plain(r) for r in df.select(*names).collect())
    assert have == want


@pytest.mark.parametrize("name", ["w1_cdf_curves", "w9_real_time_r4", "decode_conditioning", "scheme_advice"])
def test_query_gives_rows(spark, sf, name):
    assert QUERIES[name](spark, sf).count() > 0


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() == 75
    assert set(catalog.queries()) <= set(__spark_entry__.queries())


def test_oracles_name_queries():
    assert set(ORACLES) <= set(QUERIES)


def test_training_converges_to_least_squares(spark, sf):
    sample = exact_sample(spark, sf, 6).select("batch", "x0", "x1", "y")
    scale = (1.0, 0.02, 1e-7)
    theta = train.descend(sample, 3000, 1e-3, scale)[-1]
    rows = np.array(sample.select("x0", "x1", "y").collect(), float) * scale
    best = np.linalg.lstsq(rows[:, :2], rows[:, 2], rcond=None)[0]
    assert np.allclose(theta, best, atol=1e-4)


def test_schemes_give_the_same_descent(spark, sf):
    sample = exact_sample(spark, sf, 6).select("batch", "x0", "x1", "y")
    runs = [train.coded_descend(sample, s, 5, 1e-4, (1.0, 0.02, 1e-7))[-1] for s in (scheme("wait_all", 6), scheme("gradcode_layered", 6, 3, orders=(3, 2)), scheme("gradcode_shared", 6, 3, order=2, P=2), scheme("gradcode_hybrid", 6, 3, orders=(3, 2), P=2))]
    for r in runs[1:]:
        assert np.allclose(r, runs[0], rtol=1e-9)


def test_tolerance_may_change_over_rounds():
    s = scheme("uncoded_partial", 20, 4, tolerance=lambda t: 0.2 if t < 5 else 0.0)
    assert s.at_round(0).tolerance == 0.2
    assert s.at_round(9).tolerance == 0.0


def test_splits_and_padding_of_empty_tables(spark, sf):
    none = exact_sample(spark, sf, 5).where("false")
    assert regress.partial_gradients(none, (1, 2, 3, 4, 5)).count() == 0
    assert regress.pad_blocks(none, ["y"]).count() == 0


def test_joins_with_nulls_and_ties(spark):
    left = spark.createDataFrame([("a", 1), ("a", 5), ("b", 2), (None, 3)], "k string, at int")
    right = spark.createDataFrame([("a", 1, 10), ("a", 4, 40), ("b", 3, 30)], "k string, at int, v int")
    got = {(r.k, r.at): r.last_v for r in relops.as_of(left, right, "k", "at", "v").collect()}
    assert got == {("a", 1): 10, ("a", 5): 40, ("b", 2): None, (None, 3): None}


def test_relational_completion_equals_vector_replay(spark):
    """The table form and the array form of the recovery rule, on the same rounds."""
    from tolerant_gd.operators import layout
    from tolerant_gd.operators.simulate import Replay

    rng = np.random.default_rng(4)
    unit = rng.integers(50, 900, (15, 12))
    lat = spark.createDataFrame([(t, w, int(unit[t, w]), 0) for t in range(15) for w in range(12)], "trial long, worker int, unit long, start long")
    schemes = [scheme("gradcode_layered", 12, 3, orders=(3, 1), P=2), scheme("uncoded_multi", 12, 3), scheme("gradcode_hybrid", 12, 4, orders=(4, 2), P=3), scheme("uncoded_single", 12, 3), scheme("lagrange_multi", 12, 4, polys=2)]
    done = recover.complete(recover.arrivals(lat, layout.message_table(spark, schemes))).collect()
    for i, s in enumerate(schemes):
        p = Replay(s)
        ends, loads = p.complete(p.ready(unit.astype(float), np.zeros((15, 12))))
        mine = sorted((r.trial, r.t, r.load) for r in done if r.sid == i)
        assert mine == [(t, int(ends[t]), int(loads[t])) for t in range(15)]


def test_plans_are_what_they_should_be(spark, sf, capsys):
    """Gradients read only feature columns and shuffle partial sums."""
    regress.partial_gradients(exact_sample(spark, sf, 20).select("batch", "x0", "x1", "y"), (1, 2)).explain("formatted")
    plan = capsys.readouterr().out
    assert "l_shipdate" not in plan
    assert plan.count("Exchange") <= 3
    assert "partial_sum" in plan
    filtered = spark.read.parquet(f"{sf}/lineitem.parquet").where(F.col("l_quantity") > 49).select("l_orderkey")
    filtered.explain("formatted")
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,49.0)]" in capsys.readouterr().out


def test_cross_products_of_blocks_cover_all_rows(spark, sf):
    """Every row is in the cross products; messages decoded from them are exact, and their residual is that of the rows."""
    from tolerant_gd.operators import lagrange

    xs, K = [f"x{i}" for i in range(5)], 6
    rows = exact_sample(spark, sf, K)
    grams = lagrange.cross_grams(regress.pad_blocks(rows, ["l_orderkey", "x4", "y", "x1", "x2", "x3"]), xs, K)
    x = np.array(rows.select(*xs).collect(), np.int64)
    z = [1000, 2000, -300, 50, 7]
    assert (sum(grams[b, b] for b in range(K)) == x.T @ x).all()
    for r, polys in ((3, 3), (3, 1), (4, 2)):
        code = lagrange.Code(K, r, polys)
        sent = lagrange.message_grams(grams, code)
        last = list(range(K * code.draws))[-code.threshold :]
        assert lagrange.decode_product(sent, z, code, last) == (x.T @ x @ np.array(z)).tolist()
        sent[last[0]] = sent[last[0]] + 1
        assert lagrange.decode_product(sent, z, code, last) != (x.T @ x @ np.array(z)).tolist()
        floats = lagrange.Code(K, r, polys, exact=False)
        assert lagrange.gram_residual(grams, z, floats, list(range(floats.threshold))) < 1e-3


def test_no_query_reads_a_part_of_a_table():
    for name in ["lagrange_decode_single", "lagrange_decode_multi", "lagrange_decode_two_polys", "lagrange_decode_padded", "lagrange_encode_rows", "op_window_ranks"]:
        assert "key <" not in ORACLES[name]


def test_field_arithmetic():
    from tolerant_gd.functions import field

    p, rng = field.PRIME, np.random.default_rng(4)
    a = np.concatenate([rng.integers(0, p, 500), [0, 1, p - 1, p - 1, (1 << 31) - 1]]).astype(np.uint64)
    b = np.concatenate([rng.integers(0, p, 500), [p - 1, p - 1, p - 1, 1, 1 << 31]]).astype(np.uint64)
    assert field.times(a, b).tolist() == [int(x) * int(y) % p for x, y in zip(a, b, strict=True)]
    assert int(field.total(a)) == sum(map(int, a)) % p
    assert field.elements(np.array([-1, 5])).tolist() == [p - 1, 5]


def test_measurements_are_numbered_alike_in_any_slices(spark, sf, monkeypatch):
    from tolerant_gd.sources import tables

    want = sorted(map(tuple, tables.measurements(spark, sf).collect()))
    monkeypatch.setattr(tables, "ID_SLICE", 37)
    assert sorted(map(tuple, tables.measurements(spark, sf).collect())) == want
    assert len({(w, k, i) for w, k, i, _ in want}) == len(want)


def test_padding_in_short_runs(spark):
    rows = [(b, i, 1, i) for b, n in ((0, 9), (1, 2), (2, 5)) for i in range(n)]
    got = regress.pad_blocks(spark.createDataFrame(rows, "batch int, x0 long, x1 int, y long"), ["x0"], run=2).collect()
    assert sorted((r.batch, r.pos) for r in got) == [(b, p) for b in range(3) for p in range(9)]
    assert {(r.batch, r.pos, r.x0) for r in got if r.x1} == {(b, i, i) for b, i, _, _ in rows}


@pytest.mark.parametrize("name,polys", [("lagrange_multi", 1), ("lagrange_multi", 3), ("lagrange_single", None)])
def test_lagrange_descent_uses_its_messages(spark, sf, monkeypatch, name, polys):
    """The decoded descent equals the plain one, and no longer does so with one wrong weight."""
    from tolerant_gd.operators import lagrange

    sample, scale = exact_sample(spark, sf, 6).select("batch", "x0", "x1", "y"), (1.0, 0.02, 1e-7)
    s = scheme(name, 6, 3, **({"polys": polys} if polys else {}))
    want = train.descend(sample, 3, 1e-4, scale)[-1]
    assert np.allclose(train.coded_descend(sample, s, 3, 1e-4, scale)[-1], want, rtol=1e-9)
    right = lagrange.Code.decode_coefs
    monkeypatch.setattr(lagrange.Code, "decode_coefs", lambda self, got: [(i, w + (k == 0)) for k, (i, w) in enumerate(right(self, got))])
    assert not np.allclose(train.coded_descend(sample, s, 3, 1e-4, scale)[-1], want, rtol=1e-9)


def test_window_ranks_of_all_orders(spark, sf):
    assert QUERIES["op_window_ranks"](spark, sf).count() == spark.read.parquet(f"{sf}/orders.parquet").count()


def test_experiments_have_their_stated_sizes(spark, sf):
    from tolerant_gd.catalog import workloads

    assert QUERIES["w1_cdf_curves"](spark, sf).agg(F.sum("n")).first()[0] == 100_000
    assert workloads._rounds.__defaults__[-1] == 1_000
    assert {r.trials for r in QUERIES["w10_congestion_whole"](spark, sf).collect()} == {1_000}


def test_rounds_of_more_codes_than_a_word_has_bits(spark, tmp_path):
    """Two hundred codes over two files: the state between them holds all of a round's codes."""
    from tolerant_gd.streaming import detector

    folder = str(tmp_path / "m")
    for part in (range(0, 150), range(100, 200)):
        rows = spark.createDataFrame([(0, i, i) for i in part], "round long, code int, seq long").selectExpr("round", "0 worker", "code", "seq", "timestamp_seconds(1700000000 + seq) ts")
        rows.coalesce(1).write.mode("append").parquet(folder)
    live = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got = detector.run_to_table(detector.completions(live, 190), "many_codes").collect()
    assert [(r.round, r.codes, r.distinct) for r in got] == [(0, 190, True)]
    loads = detector.run_to_table(detector.tumbling(live, "1 day", "1 second"), "many_loads", "complete").collect()
    assert [(r.load, r.codes) for r in loads] == [(250, 200)]


def test_training_traces_decode_their_gradients(spark, sf, monkeypatch):
    """Schemes that recover the gradient in full have one trace of the loss; a wrong weight shows in it."""
    from tolerant_gd.catalog import gradients
    from tolerant_gd.operators import lagrange

    def losses(rounds):
        out = {}
        for r in gradients._training(spark, sf, rounds, (scheme("gradcode_single", 20, 4), *gradients._TRACED)).collect():
            out.setdefault(r.scheme, []).append(r.loss)
        return out

    got = losses(25)
    assert np.allclose(got["lagrange_multi"], got["wait_all"], atol=2e-6)
    assert np.allclose(got["gradcode_single"], got["wait_all"], atol=2e-6)
    assert got["wait_all"][-1] < got["wait_all"][0]
    right = lagrange.Code.decode_coefs
    monkeypatch.setattr(lagrange.Code, "decode_coefs", lambda self, have: [(i, w + (k == 0)) for k, (i, w) in enumerate(right(self, have))])
    assert not np.allclose(losses(3)["lagrange_multi"], got["wait_all"][:3], atol=1e-3)


def test_streams_run_into_tables_not_into_the_driver(spark, sf):
    """No sink holds its rows in the driver's memory; a result is files, and the last batch of a complete mode is all of it."""
    got = QUERIES["stream_static_join"](spark, sf)
    assert got.inputFiles()
    assert not [t.name for t in spark.catalog.listTables() if t.isTemporary and t.name.startswith("stream_result")]
    assert got.agg(F.sum("n")).first()[0] == spark.read.parquet(f"{sf}/events.parquet").count()


def test_loss_beyond_64_bits(spark):
    """Sums of squares that no bigint holds are exact decimals; others stay bigints."""
    from tolerant_gd.catalog import gradients

    def losses(y, n):
        rows = spark.range(n).selectExpr("cast(id % 2 as int) batch", "0L x0", "0L x1", "0L x2", "0L x3", "0L x4", f"{y}L y")
        return gradients._loss(rows)

    assert sorted(map(tuple, losses(2_000_000_000, 10).collect())) == [(0, 5 * 4 * 10**18), (1, 5 * 4 * 10**18)]
    few = losses(3, 10)
    assert dict(few.dtypes)["twice_loss"] == "bigint"
    assert sorted(map(tuple, few.collect())) == [(0, 45), (1, 45)]


FROM_TABLES = ["cdf_lagrange_single", "cdf_layered", "cdf_message_threshold", "cdf_worker_threshold", "common_codes", "decoding_operations", "expected_by_integration", "expected_completion", "expected_order_statistic", "latency_initial_delay", "latency_shifted_exp"]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_model_queries_read_a_table(spark, sf, name):
    assert any("events" in f for f in QUERIES[name](spark, sf).inputFiles())


def test_conditioning_is_that_of_the_given_gradients(spark, sf):
    from pyspark.errors import AnalysisException

    from tolerant_gd.operators import polycode

    with pytest.raises(AnalysisException):
        QUERIES["decode_conditioning"](spark, f"{sf}/none")
    assert all(r.growth >= 1 for r in QUERIES["decode_conditioning"](spark, sf).collect())
    masks = polycode.supports([(w, j, (w + j) % 6) for w in range(6) for j in range(3)])
    alike, one = {0: dict.fromkeys(range(6), 7)}, [{0: {b: -5}} for b in range(6)]
    assert max(polycode.growth(masks, [0, 1, 2, 3], g) for g in one) == pytest.approx(polycode.conditioning(masks, [0, 1, 2, 3]))
    assert polycode.growth(masks, [0, 1, 2, 3], alike) <= polycode.conditioning(masks, [0, 1, 2, 3])
    assert polycode.growth(masks, [0, 1, 2, 3], {0: {0: 1, 1: -1}}) == 0


ODD_EVENTS = {
    "alike": "3.0::DOUBLE AS value, event_id * 7 AS user_id",
    "one": "value, event_id * 7 AS user_id WHERE event_id = 1",
}


def odd_events(tmp_path, columns):
    """A folder whose events are 400 rows with these columns, and a connection to them."""
    what, _, where = columns.partition(" WHERE ")
    con, path = duckdb.connect(), f"{tmp_path}/events.parquet"
    base = "SELECT i AS event_id, TIMESTAMP '2024-01-01' + to_seconds(i) AS ts, ['view', 'click', 'purchase', 'error', 'signup'][1 + i % 5] AS event_type, round((i * 37 % 1000) / 10.0, 2)::DOUBLE AS value, '{}' AS props FROM range(400) t(i)"
    con.execute(f"COPY (SELECT event_id, ts, event_type, props, {what} FROM ({base}) WHERE {where or 'true'}) TO '{path}' (FORMAT parquet)")
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{path}'")
    return str(tmp_path), con


@pytest.mark.parametrize("odd", ["alike", "one"])
@pytest.mark.parametrize("name", ["cdf_layered", "cdf_message_threshold", "cdf_worker_threshold"])
def test_distributions_of_equal_times_are_steps(spark, tmp_path, name, odd):
    """Measured times without any spread have no rate; the SQL gives a step from 0 to 1."""
    folder, con = odd_events(tmp_path, ODD_EVENTS[odd])
    test_query_equals_sql(spark, con, folder, name)
    assert {r.cdf for r in QUERIES[name](spark, folder).collect()} == {0.0, 1.0}


@pytest.mark.parametrize("odd", ["alike", "one"])
def test_order_statistics_of_equal_times(spark, tmp_path, odd):
    folder, con = odd_events(tmp_path, ODD_EVENTS[odd])
    test_query_equals_sql(spark, con, folder, "expected_order_statistic")


@pytest.mark.parametrize("odd", ["event_id * 7 - 700 AS user_id", "CASE WHEN event_id % 3 > 0 THEN event_id * 7 END AS user_id"])
@pytest.mark.parametrize("name", ["latency_initial_delay", "latency_shifted_exp"])
def test_fitted_workers_are_those_of_the_events(spark, tmp_path, name, odd):
    """Workers of negative user ids, and events without a user, as in the SQL."""
    folder, con = odd_events(tmp_path, f"value, {odd}")
    test_query_equals_sql(spark, con, folder, name)


def test_initial_delay_reads_events_once(spark, sf):
    assert QUERIES["latency_initial_delay"](spark, sf)._jdf.queryExecution().executedPlan().toString().count("FileScan") == 1
