"""Searches, losses, optimisers and passes against closed forms and each other."""

import math

import numpy as np
import pytest

from rayfit import losses, optim, taylor, wolfe

SF = "/root/testdata/sf0.001"


def test_worked_example():
    want = {2: 1.518724324, 3: 1.572111058, 4: 1.534974610, 5: 1.535434241, 6: 1.534925043, 7: 1.534923124}
    for d, alpha in want.items():
        assert 1 + taylor.scalar_expand(taylor.worked_example, d)(1.0).argmin().t == pytest.approx(alpha, abs=1e-9)
    step = taylor.taylor_line_search(taylor.scalar_expand(taylor.worked_example, 3), 1.0)
    assert step.n_eval == 2 and step.alpha == pytest.approx(1.534907558, abs=1e-9)
    f = taylor.worked_example
    base = wolfe.line_search(lambda a: (f(a, 0), f(a, 1), None), f(0, 0), f(0, 1))
    assert base.alpha == 1.0 and base.n_eval == 1
    assert taylor.exact_line_search(taylor.scalar_expand(f, 7)).alpha == pytest.approx(1.5349191320, abs=1e-9)


def test_argmin_cases():
    assert taylor.TaylorModel([1, -1, 0.5]).argmin().t == 1.0
    assert taylor.TaylorModel([0, 1, 0.5], 0.5).argmin().status == "fallback"  # the minimum lies behind the start
    assert taylor.TaylorModel([0, -1, 0]).fallback() == math.inf
    for how in ("newton", "bisect", "roots"):
        assert taylor.TaylorModel([0, -3, 0.5, 1]).argmin(how).t == pytest.approx((-1 + math.sqrt(37)) / 6)


@pytest.mark.parametrize("degree", [2, 3, 5, 7])
def test_logistic_terms_by_differences(degree):
    z, q = np.array([-2.0, 0.3, 4.0]), np.array([1.0, -0.7, 0.2])
    for y in (np.zeros(3), np.array([1.0, 5.0, -1.0])):
        c = losses.Logistic().kernel(z, q, y, degree)
        for t in (0.1, 0.2):
            model = sum(c[k] * t**k for k in range(degree + 1))
            assert np.all(np.abs(losses.Logistic().value(z + t * q, y) - model) <= 0.05 * t ** (degree + 1))


def test_extreme_margins_stay_finite():
    z = np.array([-800.0, 800.0, 0.0])
    assert np.isfinite(losses.Logistic().kernel(z, np.ones(3), np.array([0.0, 1.0, 0.0]), 5)).all()


def test_l1_is_refused():
    with pytest.raises(ValueError):
        losses.L1(0.1)


def test_custom_loss_is_checked():
    ls = losses.LeastSquares()
    losses.Custom(ls.kernel, ls.value, ls.slope, 2)
    with pytest.raises(ValueError):
        losses.Custom(lambda z, q, y, d: ls.kernel(z, 2 * q, y, d), ls.value, ls.slope)


def test_all_pairs_reach_one_loss():
    g = np.random.default_rng(1)
    x = np.c_[g.normal(size=(500, 4)), np.ones(500)]
    y = (x @ g.normal(size=5) + g.logistic(size=500) > 0).astype(float)
    ends = [optim.minimize(optim.ArrayProblem(x, y, losses.Logistic(), 1e-3), m, s, theta=1e-6, max_iter=80).trace[-1]["loss"] for m in ("gd", "ncg", "lbfgs") for s in ("taylor", "wolfe")]
    assert max(ends) - min(ends) < 1e-9


def test_separable_and_single_rows_end():
    x, y = np.array([[1.0], [-1.0]]), np.array([1.0, 0.0])
    assert np.isfinite(optim.minimize(optim.ArrayProblem(x, y, losses.Logistic()), "lbfgs", "taylor", max_iter=15).trace[-1]["loss"])
    assert optim.minimize(optim.ArrayProblem(x[:1], y[:1], losses.LeastSquares()), "lbfgs", "taylor", degree=2).trace[-1]["loss"] == pytest.approx(0, abs=1e-20)


def test_two_loop_on_dots():
    g, rule = np.random.default_rng(2), optim.Lbfgs(5)
    rule.pairs = [(s, s * np.arange(1, 7)) for s in g.normal(size=(4, 6))]
    grad = g.normal(size=6)
    basis = np.array([s for s, _ in rule.pairs] + [y for _, y in rule.pairs] + [grad])
    assert np.allclose(optim.two_loop_dots(basis @ basis.T, 4) @ basis, rule.direction(grad)[0])


def test_plans_agree(spark):
    from pyspark.sql import functions as F

    from rayfit import workloads as W
    from rayfit.instances import Instances, Problem

    d = W.planted(spark, SF)
    w, p = np.array([0.1, -0.2, 0.3, -0.1, 0.05]), np.array([0.5, -0.5, 0.1, 0.2, 0.1])
    x = F.array("x1", "x2", "x3", "x4", "x5")
    idx = F.array(*map(F.lit, range(5)))
    kinds = [W.w9(spark, SF).data, Instances(d.select("y", x.alias("x")), 5, kind="dense"), Instances(d.select("y", idx.alias("idx"), x.alias("val")), 5, kind="sparse")]
    got = []
    for data in kinds:
        for how in ("flat", "tree"):
            problem = Problem(data, losses.Logistic(), 1e-3, reduce=how, cached=how == "tree")
            problem.begin_ray(w, p)
            got.append(np.r_[problem.coefficients(w, p, 0.5, 5).c, problem.value_and_gradient(w)[1]])
            problem.end_ray()
        assert not any(data.validate().values())
    assert all(np.allclose(g, got[0], rtol=1e-11, atol=1e-13) for g in got)


def test_queries_run_and_match_sql(spark):
    duckdb = pytest.importorskip("duckdb")
    from rayfit import queries

    con = duckdb.connect()
    for t in ("lineitem", "part", "embeddings", "events", "orders", "customer"):
        con.execute(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    sql = queries.oracle_sql()
    for name in ("coeffs_logit_w9_d5", "coeffs_table_w9_d5", "coeffs_mf_w7a_d4", "auc_w9", "trace_speedup", "sql_terms_w9", "coeffs_logit_w1_d5", "ncg_taylor_w1_3iters", "lbfgs_wolfe_w9_3iters", "wolfe_bracket", "sql_functions"):
        a, b = queries.queries()[name](spark, SF).toArrow(), con.execute(sql[name]).to_arrow_table()
        cols = sorted(a.column_names)
        assert cols == sorted(b.column_names)
        assert sorted(zip(*[a[c].to_pylist() for c in cols])) == sorted(zip(*[b[c].to_pylist() for c in cols])), name


@pytest.mark.parametrize(("search", "share", "each", "longest"), [("taylor", 8, 500, 7), ("wolfe", 4, 100, 10)])
def test_searches_longer_than_the_sql_are_whole(spark, tmp_path, monkeypatch, search, share, each, longest):
    """Where a search takes more steps than the SQL is unrolled to, the rows are those of SQL unrolled further."""
    duckdb = pytest.importorskip("duckdb")
    from rayfit import oracles, queries

    con, path = duckdb.connect(), f"{tmp_path}/embeddings.parquet"
    con.execute(f"""copy (select vec_id, label, list_transform(embedding, lambda x: (x / {share})::float) as embedding from '{SF}/embeddings.parquet'
      qualify row_number() over (partition by label < 5 order by vec_id) <= {each} order by vec_id) to '{path}' (format parquet)""")
    con.execute(f"create view embeddings as from '{path}'")
    ours = sorted(map(tuple, queries.first_iterates("w1", "ncg", search)(spark, str(tmp_path)).collect()))
    assert max(row[4] for row in ours) == longest > {"taylor": oracles.EXPANSIONS, "wolfe": oracles.EVALUATIONS}[search]
    monkeypatch.setattr(oracles, "EXPANSIONS", 10)
    monkeypatch.setattr(oracles, "EVALUATIONS", 25)
    assert ours == sorted(con.execute(oracles.trace("w1", "ncg", search, *queries.SETTINGS["w1"])).fetchall())


def test_libsvm_round_trip(spark, tmp_path):
    from rayfit import sources

    df = spark.createDataFrame([([0, 3, 5], [1.5, -2.0, 1.0], 1.0), ([5], [1.0], 0.0)], "idx array<int>, val array<double>, y double")
    sources.write_libsvm(df, str(tmp_path / "x"), 5)
    assert sorted(map(tuple, sources.read_libsvm(spark, str(tmp_path / "x"), 5).select("idx", "val", "y").collect())) == sorted(map(tuple, df.collect()))


def test_estimator(spark):
    from rayfit.modeling import RayRegression

    df = spark.createDataFrame([([float(k)], float(k > 3)) for k in range(8)], "features array<double>, label double")
    out = RayRegression(regParam=1e-3).fit(df).transform(df)
    assert out.filter("prediction = label").count() == 8


def test_stream_of_batches(spark, tmp_path):
    from rayfit import streaming
    from rayfit import workloads as W

    events = spark.read.parquet(f"{SF}/events.parquet")
    events.limit(200).write.parquet(str(tmp_path / "in"))
    learner = streaming.MiniBatch(lambda b: W.w15(b).data.df, 126, losses.Logistic())
    stream = spark.readStream.schema(events.schema).parquet(str(tmp_path / "in"))
    streaming.start(stream, learner, str(tmp_path / "ck")).awaitTermination(120)
    assert sum(t["n"] for t in learner.trace) == 200
    learner(events, learner.seen)  # a repeated batch changes nothing
    assert sum(t["n"] for t in learner.trace) == 200


def test_minibatch_query_takes_every_day(spark):
    from rayfit import queries

    days = spark.read.parquet(f"{SF}/events.parquet").selectExpr("to_date(ts) AS d").groupBy("d").count().orderBy("d").collect()
    got = queries.minibatch_w15(spark, SF).orderBy("batch").collect()
    assert len(days) > 6 and [(r.batch, r.n) for r in got] == [(k, d["count"]) for k, d in enumerate(days)]


def test_table_learner_takes_the_same_steps(spark):
    """Weights in a table and weights on the driver: equal losses, steps and weights, constant feature included."""
    from rayfit import tables

    rng = np.random.default_rng(5)
    x = rng.normal(size=(120, 4)) * (rng.random((120, 4)) < 0.7)
    x[7] = 0  # a row without any feature
    y = (x @ [1, -2, 0.5, 0] + 0.3 + rng.logistic(size=120) > 0).astype(float)
    ex = spark.createDataFrame([(i, f, float(x[i, f])) for i in range(120) for f in range(4) if x[i, f]], "row_id long, f long, v double")
    labels = spark.createDataFrame([(i, float(v)) for i, v in enumerate(y)], "row_id long, y double")
    params, bias, trace = tables.minimize(ex, labels, losses.Logistic(), 1e-2, max_iter=5, theta=1e-6, history=3)
    fit = optim.minimize(optim.ArrayProblem(np.c_[x, np.ones(120)], y, losses.Logistic(), 1e-2), "lbfgs", "taylor", max_iter=5, theta=1e-6, history=3)
    assert [t["loss"] for t in trace] == pytest.approx([t["loss"] for t in fit.trace], abs=1e-12)
    assert [r["w"] for r in params.orderBy("f").collect()] + [bias] == pytest.approx(list(fit.w), abs=1e-9)
    empty = tables.minimize(ex.limit(0), labels.limit(0), losses.Logistic())
    assert empty[2] == [] and empty[0].count() == 0


def test_products_with_the_second_derivative(spark):
    from rayfit import workloads as W
    from rayfit.instances import Problem

    data = W.w9(spark, SF).data
    rows = data.df.select("x1", "x2", "x3", "x4", "x5", "y").toPandas().to_numpy()
    same = optim.ArrayProblem(rows[:, :5], rows[:, 5], losses.Logistic(), 1e-3)
    w, d = np.array([0.3, -0.2, 0.1, 0.0, 0.5]), np.array([1.0, 2.0, -1.0, 0.5, 0.1])
    exact = same.curvature_product(w, d)
    assert Problem(data, losses.Logistic(), 1e-3).curvature_product(w, d) == pytest.approx(exact, rel=1e-9)
    assert (same.gradient(w + 1e-6 * d) - same.gradient(w - 1e-6 * d)) / 2e-6 == pytest.approx(exact, rel=1e-5)
    fit = optim.minimize(same, "newton", "taylor", theta=1e-6, max_iter=12)
    assert fit.trace[-1]["loss"] == pytest.approx(optim.minimize(same, "lbfgs", "taylor", theta=1e-6).trace[-1]["loss"], abs=1e-12)
    assert optim.minimize(same, "ncg", "taylor", precondition=optim.diagonal(same, np.zeros(5)), max_iter=60).trace[-1]["grad_norm"] < 1e-4


def test_accuracy_plateau_ends_a_fit():
    stop = optim.stop_rule(100, acc_gain=1e-2, acc_span=2)
    assert [stop(k, 1.0, None, x) for k, x in enumerate((0.6, 0.5, 0.4, 0.399, 0.398))] == [False, False, False, False, True]


def test_factorization_plans_stay_short(spark):
    """Each iteration reads staged factors: losses fall, and what the last one reads is no longer than the first."""
    from rayfit import factorization

    g = np.random.default_rng(0)
    u, v = g.normal(size=(12, 2)), g.normal(size=(9, 2))
    ratings = spark.createDataFrame([(i, j, float(u[i] @ v[j])) for i in range(12) for j in range(9) if (i + j) % 3], "i long, j long, value double")
    a, _, trace = factorization.fit(ratings, 2, 1e-4, max_iter=3)
    assert [t["loss"] for t in trace] == sorted((t["loss"] for t in trace), reverse=True)
    assert len(a._jdf.queryExecution().logical().toString()) < 1000
    assert factorization.fit(ratings.limit(0), 2)[2] == []


def test_text_weights_samples_and_sources(spark, tmp_path):
    from rayfit import features, measures, sources, sqlfuncs

    df = spark.createDataFrame([(0, [0, 1, 4], [0.6, 0.8, 1.0], 1.0), (1, [0, 4], [1.0, 1.0], 0.0), (2, [4], [1.0], 1.0)], "row_id long, idx array<int>, val array<double>, y double")
    got = {r.row_id: (r.idx, r.val) for r in features.idf(df).collect()}
    a, b = 0.6 * (np.log(4 / 3) + 1), 0.8 * (np.log(4 / 2) + 1)
    assert got[0][0] == [0, 1, 4] and got[0][1] == pytest.approx([a / np.hypot(a, b), b / np.hypot(a, b), 1.0]) and got[2] == ([4], [1.0])
    assert features.to_sparse(spark.createDataFrame([([0.0, 2.0, 0.0, 3.0],)], "x array<double>")).first().asDict() == {"idx": [1, 3], "val": [2.0, 3.0]}
    sources.write_libsvm(df, str(tmp_path / "svm"), 4)
    spark.dataSource.register(sources.LibsvmSource)
    back = spark.read.format("rayfit_libsvm").option("m", "4").load(str(tmp_path / "svm"))
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, sources.read_libsvm(spark, str(tmp_path / "svm"), 4).collect()))
    assert features.hash_sample(spark.range(2000), "id", 0.25).count() == pytest.approx(500, abs=80)
    assert str(measures.exact_sum(spark.createDataFrame([(0.1,)] * 10, "x double"), "x", 3).first().total) == "1.000"
    sqlfuncs.register(spark)
    x = spark.createDataFrame([([float(k)], float(k > 3)) for k in range(8)], "x array<double>, y double")
    x.createOrReplaceTempView("small")
    w = [r.w for r in spark.sql("SELECT * FROM fit_logistic(TABLE(SELECT * FROM small) WITH SINGLE PARTITION, lam => 1e-2D) ORDER BY i").collect()]
    assert len(w) == 2 and w[0] > 0 > w[1]


def test_cross_validation_and_state(spark, tmp_path):
    from rayfit import modeling, sources

    g = np.random.default_rng(4)
    x = np.c_[g.normal(size=(90, 2)), np.ones(90)]
    y = (x @ [2, -1, 0.3] + g.logistic(size=90) > 0).astype(float)
    df = spark.createDataFrame([(i, a.tolist(), float(b)) for i, (a, b) in enumerate(zip(x, y))], "id long, x array<double>, y double")
    out = modeling.cross_validate(df, "id", [1.0, 1e-2], 2, max_iter=8).collect()
    assert len(out) == 4 and sum(r.n for r in out) == 180 and min(r.log_loss for r in out) < 0.69
    whole = optim.ArrayProblem(x, y, losses.Logistic(), 1e-3)
    first = optim.minimize(whole, max_iter=4)
    sources.save_state(spark, str(tmp_path / "state"), 4, first)
    state = sources.load_state(spark, str(tmp_path / "state"))
    rest = optim.minimize(whole, max_iter=3, state={k: state[k] for k in ("w", "rule")})
    straight = optim.minimize(whole, max_iter=7)
    assert rest.trace[-1]["loss"] == pytest.approx(straight.trace[-1]["loss"], abs=1e-13)


def test_traces_by_wolfe_need_more_iterations(spark):
    """What the experiments say: at equal accuracy the Taylor search needs fewer iterations where parameters outnumber rows."""
    from rayfit import experiments

    with experiments.prepared(spark, SF, "w3", m=1 << 14) as work:
        fits = {s: experiments.fitted(work, "w3", "lbfgs", s, 8) for s in ("taylor", "wolfe")}
        report = experiments.cost_report(fits["taylor"], work.data)
    assert fits["taylor"].trace[-1]["loss"] < fits["wolfe"].trace[-1]["loss"]
    assert report["iterations"] == 8 and report["passes"]["g"][0] >= 8 and report["plan"]


def test_whole_vectors_come_one_partition_at_a_time(spark, monkeypatch):
    """a flat sum of 32 vectors of 2^18 parameters never gathers them together on the driver."""
    from pyspark.sql.classic.dataframe import DataFrame

    from rayfit import instances

    m = 1 << 18
    df = spark.range(64).repartition(32).selectExpr("array(cast(id * 4096 as int)) AS idx", "array(1D) AS val", "cast(id % 2 as double) AS y")
    data = instances.Instances(df, m, kind="sparse")
    data.count()
    plain, most = DataFrame.collect, []
    monkeypatch.setattr(DataFrame, "collect", lambda self: most.append(len(r := plain(self))) or r)
    got = [instances.Problem(data, losses.Logistic(), reduce=how).value_and_gradient(np.zeros(m)) for how in ("flat", "tree")]
    assert data.parts * m > instances.FLAT_LIMIT and max(most, default=0) <= 1 + -(-m // instances.BLOCK)
    assert got[0][0] == pytest.approx(got[1][0]) and np.allclose(got[0][1], got[1][1])


def test_rows_are_weighed_once_and_packed(spark):
    """F3 to F11: a row's norm is no part of the work for each of its values, and persisted rows lie in few partitions."""
    from pyspark.sql import functions as F

    from rayfit import features, instances

    docs = spark.createDataFrame([(0, ["a", "b", "a", None]), (1, []), (2, None), (3, ["c"] * 3)], "k long, w array<string>")
    rows = features.hashed(docs, "k", F.col("w"), 8, F.col("k") % 2 == 1, stable=True)
    assert "/ SQRT(" not in rows._jdf.queryExecution().optimizedPlan().toString().upper()
    got = {r.row_id: r for r in rows.collect()}
    size = np.hypot(1 + np.log(2), 1)
    assert sorted(got[0].val) == pytest.approx(sorted([(1 + np.log(2)) / size, 1 / size, 1.0])) and got[0].idx == sorted(got[0].idx)
    assert (got[1].idx, got[2].idx, got[3].val, got[3].y) == ([8], [8], [1.0, 1.0], 1.0)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    try:
        data = instances.Instances(rows, 9, kind="sparse").persist()
        assert data.count() == 4 and data.packed.rdd.getNumPartitions() < 16
        whole = instances.Problem(instances.Instances(rows, 9, kind="sparse"), losses.Logistic())
        w = np.sin(np.arange(9))
        packed = instances.Problem(data, losses.Logistic())
        assert np.allclose(packed.value_and_gradient(w)[1], whole.value_and_gradient(w)[1]) and np.allclose(packed.coefficients(w, w, 0.5, 5).c, whole.coefficients(w, w, 0.5, 5).c)
        data.unpersist()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


def test_fewer_buckets_are_remainders(spark):
    """words are hashed once for all numbers of parameters."""
    from rayfit import features
    from rayfit import workloads as W

    most = W.slots(spark, SF, "w3", 1 << 12)
    assert sorted(map(tuple, features.folded(most, 1 << 8).collect())) == sorted(map(tuple, W.slots(spark, SF, "w3", 1 << 8).collect()))


@pytest.mark.parametrize("name", ["comm_cost", "cubic_min_cases", "example_1d_taylor", "example_1d_wolfe", "horner_grid", "pass_model", "plateau_toy", "speedup_windows", "sql_functions", "timing_rollup", "timing_table", "to_gap_toy"])
def test_results_follow_the_tables(spark, name):
    """F14 to F25: each job's rows come from a given table, so that two sizes of it give two results, each equal to SQL."""
    duckdb = pytest.importorskip("duckdb")
    from rayfit import queries

    got = []
    for sf in (SF, SF.replace("0.001", "0.01")):
        con = duckdb.connect()
        for t in ("lineitem", "part", "events", "orders"):
            con.execute(f"create view {t} as select * from read_parquet('{sf}/{t}.parquet')")
        a, b = queries.queries()[name](spark, sf).toArrow(), con.execute(queries.oracle_sql()[name]).to_arrow_table()
        rows = [sorted(map(repr, zip(*[x[c].to_pylist() for c in sorted(a.column_names)]))) for x in (a, b)]
        assert rows[0] == rows[1]
        got.append(rows[0])
    assert got[0] != got[1]


def test_timing_holds_one_fit_and_one_plan(spark, monkeypatch):
    """F8: no earlier fit's vectors lie on the driver while another runs, and the report's plan does not grow with the fits."""
    import weakref

    from rayfit import experiments

    plain, held, evals = experiments.fitted, [], {}

    def watched(work, name, method, search, *a, **b):
        assert not any(r() for r in held)
        fit = plain(work, name, method, search, *a, **b)
        held.append(weakref.ref(fit))
        evals[method, search] = np.mean([t["n_eval"] for t in fit.trace if t["k"]])
        return fit

    monkeypatch.setattr(experiments, "fitted", watched)
    out = experiments.timing(spark, SF, ("w1",), iterations=2)
    got = out.collect()
    assert [(r.dataset, r.method, r.search, r.n, r.m) for r in got] == [("w1", m, s, 500, 65) for m in ("lbfgs", "ncg") for s in ("wolfe", "taylor")]
    assert all(r.n_e == pytest.approx(evals[r.method, r.search]) and r.tau_fg > 0 and (r.tau_ls is None) == (r.search == "wolfe") for r in got)
    assert out._jdf.queryExecution().optimizedPlan().toString().count("LogicalRDD") <= 3


def test_order_lines_are_dealt_out(spark):
    """F8: w5 reads a file of one row group, whose rows do not stay in one partition."""
    from rayfit import workloads as W

    size = "spark.sql.adaptive.coalescePartitions.minPartitionSize"
    before = spark.conf.get(size)
    spark.conf.set(size, "4k")
    try:
        data = W.w5(spark, SF).data.persist()
        assert data.count() == 6000 and data.packed.filter("n > 0").rdd.map(lambda _: 1).mapPartitions(lambda r: [sum(r)]).filter(bool).count() > 1
        data.unpersist()
    finally:
        spark.conf.set(size, before)


def test_packed_rows_are_small_and_passes_have_few_tasks(spark):
    """ones, equal sizes and labels of 0 and 1 take little room, and a pass has no more tasks than run at once; sums stay the same."""
    from pyspark.sql import functions as F

    from rayfit.instances import Instances, Problem
    from rayfit.losses import Logistic

    rng = np.random.default_rng(1)
    ids = [[sorted(rng.choice(40, 3 if even else 1 + i % 4, replace=False).tolist()) for i in range(300)] for even in (True, False)]
    for idx, y, ones, wide in ((ids[0], [0.0, 1.0], True, False), (ids[0], [0.0, 1.0], False, False), (ids[1], [0.0, 1.0], False, True), (ids[1], [0.0, 2.0], False, False), ([[]] * 300, [1.0, 0.0], False, False)):
        rows = [(a, [float(1 + k) if wide else 1.0 for k in range(len(a))], y[i % 2]) for i, a in enumerate(idx)]
        df = spark.createDataFrame(rows, "idx array<int>, val array<double>, y double").repartition(16)
        plain, data = Instances(df, 40, kind="sparse"), Instances(df, 40, kind="sparse", ones=ones)
        data.persist()
        a, b, w, p = Problem(plain, Logistic(), 0.1), Problem(data, Logistic(), 0.1), rng.normal(size=40), rng.normal(size=40)
        (f, g), (f2, g2) = a.value_and_gradient(w), b.value_and_gradient(w)
        assert data.n == plain.n == 300 and data.parts > 4 and f2 == pytest.approx(f) and g2 == pytest.approx(g)
        assert b.coefficients(w, p, 0.5, 4).c == pytest.approx(a.coefficients(w, p, 0.5, 4).c)
        assert b._held()[0].rdd.getNumPartitions() <= spark.sparkContext.defaultParallelism
        assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == "10000"  # as before the passes
        size = data.packed.agg(*(F.sum(F.length(c)) for c in ("y", "size", "idx", "val"))).first()
        values = sum(map(len, idx))
        assert size[0] == 300 * (1 if y[1] in (0.0, 1.0) else 8) and size[2] == 4 * values and size[3] == (8 * values if wide else 0)
        if idx is ids[0]:
            assert size[1] < 4 * 300
        data.unpersist()


def test_one_hot_rows_pack_without_values(spark):
    """what is known to be ones does not travel to be packed, and the sums are those of the rows with values."""
    from rayfit import workloads as W
    from rayfit.instances import Problem

    work = W.w5(spark, SF, m=1 << 12)
    w, p = np.sin(np.arange(work.data.m)) / 9, np.cos(np.arange(work.data.m))
    a = Problem(work.data, work.loss, work.lam)
    before = (*a.value_and_gradient(w), a.coefficients(w, p, 0.0, 5).c)
    work.data.persist()
    assert "val" not in work.data.packed._jdf.queryExecution().analyzed().toString().split("MapInArrow")[1].split("\n")[1]
    after = (*a.value_and_gradient(w), a.coefficients(w, p, 0.0, 5).c)
    assert all(x == pytest.approx(y) for x, y in zip(before, after, strict=True))
    work.data.unpersist()
