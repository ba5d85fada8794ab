import numpy as np
import pytest
from pyspark.sql import functions as F

from featsift.functions import encode, info
from featsift.functions.criteria import ArrayOps, Criterion, Fold, get_criterion, register_criterion
from featsift.operators import baselines, counts, greedy, metrics, models, relevance, sampling, sparse
from featsift.plans import layout, planner
from featsift.plans.dataset import Dataset
from featsift.sources import workloads
from featsift.sources.workloads import GATE

SF01 = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def gate(spark):
    return workloads.lines(spark, SF01).materialized()


def test_tiny_information(spark):
    tiny = workloads.tiny(spark)
    rel = {r["feature"]: r["rel"] for r in relevance.relevance(tiny).collect()}
    assert all(abs(v) < 1e-12 for v in rel.values())
    with_b = {r["feature"]: (r["mi"], r["cmi"]) for r in relevance.redundancy(tiny, "b").collect()}
    assert with_b[0] == pytest.approx((0, 1))  # a tells the class once b is known
    with_a = {r["feature"]: r["mi"] for r in relevance.redundancy(tiny, "a").collect()}
    assert with_a[3] == pytest.approx(1)  # the copy


def test_identities_on_random_tables(spark):
    rng = np.random.default_rng(3)
    rows = [tuple(int(x) for x in r) for r in rng.integers(0, (4, 3, 2), (500, 3))]
    ds = Dataset(spark.createDataFrame(rows, "a int, b int, y int"), ["a", "b"])
    cells = counts.contingency(ds, "b")
    pair = info.mi_and_cmi(cells).where("feature = 0").first()
    rel = {r["feature"]: r["rel"] for r in relevance.relevance(ds).collect()}
    both = info.pair_info(cells).where("feature = 0").first()["pair_info"]
    given = info.cond_mutual_info(cells.where("feature = 0"), "x", "y", ["j"], ["feature"]).first()["cmi"]
    assert both == pytest.approx(rel[1] + given)
    assert given == pytest.approx(rel[0] - pair["mi"] + pair["cmi"])
    assert pair["mi"] >= 0 and pair["cmi"] >= 0


@pytest.mark.parametrize("strategy", ["arrow", "gsets", "blocks", "packed"])
def test_strategies_count_alike(spark, strategy):
    ds = Dataset(workloads.lines(spark, "/root/testdata/sf0.001").df.withColumn("tax", F.when(F.col("ln") != 2, F.col("tax"))), list(GATE))
    for j in (None, "disc"):
        if strategy == "blocks" and j:
            continue  # nulls in blocks join alike but are tested without a chosen feature
        want = sorted(map(str, counts.contingency(ds, j, "explode").select("feature", "x", "j", "y", "c").collect()))
        assert sorted(map(str, counts.contingency(ds, j, strategy).select("feature", "x", "j", "y", "c").collect())) == want


def test_blocks_of_rows_whose_order_changes(spark):
    """Every evaluation meets the rows in another order, as after an exchange between machines."""
    ds = workloads.lines(spark, "/root/testdata/sf0.001").only(["qty", "disc"])

    def shuffled(batches):
        for batch in batches:
            yield batch.take(np.random.default_rng().permutation(batch.num_rows))

    rows = ds.columns().select("qty", "disc", "y")
    moved = Dataset(rows.mapInArrow(shuffled, rows.schema), ds.features)
    want = sorted(map(str, counts.contingency(ds, "disc", "explode").select("feature", "x", "j", "y", "c").collect()))
    assert sorted(map(str, counts.contingency(moved, "disc", "blocks").select("feature", "x", "j", "y", "c").collect())) == want


#: First picks and scores at scale 0.01.
GOLDEN = {
    "mim": [("disc", 0.211925), ("disc_hi", 0.211869), ("tax", 0.203508), ("qty", 0.155144), ("qty_band", 0.058709)],
    "mrmr": [("disc", 0.211925), ("tax", 0.202570), ("qty", 0.149888), ("ls", -0.000211), ("rf", -0.000401)],
    "jmi": [("disc", 0.211925), ("tax", 0.423287), ("qty", 0.253862), ("disc_hi", 0.247004), ("qty_band", 0.100600)],
    "cmi": [("disc", 0.211925), ("tax", 0.423287), ("qty", 0.352580), ("disc_hi", 0.317274), ("qty_band", 0.226274)],
    "cmim": [("disc", 0.211925), ("tax", 0.423287), ("qty", 0.251403), ("ship_month", 0.000877), ("ln", 0.000589)],
    "icap": [("disc", 0.211925), ("tax", 0.203508), ("qty", 0.155144), ("ship_month", 0.000092), ("ln", 0.000012)],
    "mifs": [("disc", 0.211925), ("tax", 0.202570), ("qty", 0.144633), ("ls", -0.000633), ("rf", -0.001605)],
}


@pytest.mark.parametrize("criterion", GOLDEN)
def test_golden_rankings(gate, criterion):
    steps = greedy.select(gate, 5, criterion, cache=False).steps
    assert [s["name"] for s in steps] == [n for n, _ in GOLDEN[criterion]]
    assert [s["score"] for s in steps] == pytest.approx([v for _, v in GOLDEN[criterion]], abs=1e-6)


def test_lazy_and_frame_and_sequential_agree(gate):
    for criterion in ("mrmr", "cmim"):
        want = greedy.select(gate, 4, criterion, cache=False)
        lazy = greedy.select(gate, 4, criterion, lazy=True, cache=False)
        assert lazy.steps == [dict(s, score=pytest.approx(s["score"])) for s in want.steps]
        assert sum(lazy.counted) <= 9 + 8 + 7
        assert greedy.select(gate, 4, criterion, state="frame", cache=False).names == want.names
        assert [s["name"] for s in baselines.sequential(gate, 4, criterion)] == want.names


def test_stop_rules_and_ties(spark):
    tiny = workloads.tiny(spark)
    assert len(greedy.select(tiny, 99, "mrmr").steps) == 4
    assert greedy.select(tiny, 1, "mrmr").names == ["a"]  # all relevances are 0: the first feature wins
    assert greedy.select(tiny, 4, "mrmr", min_score=0.5).steps == []


def test_user_criterion_and_unknown_name(spark):
    register_criterion(Criterion("double_relevance", {}, lambda ops, r, acc, s: 2 * r))
    assert get_criterion("double_relevance").name == "double_relevance"
    fold = Fold(0.0, lambda ops, a, d, e: ops.maximum(a, d))
    assert fold.combine(ArrayOps, np.array([1.0]), np.array([2.0]), None) == 2
    with pytest.raises(ValueError):
        get_criterion("none such")


def test_sparse_cells_equal_dense_ones(spark):
    rng = np.random.default_rng(5)
    rows = [(i, f, int(rng.integers(1, 3))) for i in range(60) for f in range(6) if rng.random() < 0.3]
    classes = spark.createDataFrame([(i, int(rng.integers(0, 2))) for i in range(60)], "row_id long, y int")
    posts = spark.createDataFrame(rows, "row_id long, feature long, code int").join(classes, "row_id")
    from featsift.plans.dataset import SparseDataset

    ds = SparseDataset(posts, classes, spark.createDataFrame([(f, f"t{f}") for f in range(6)], "feature long, name string"))
    dense = ds.densified(list(range(6)))
    for j in (None, 2):
        got = sparse.contingency(ds, j).select("feature", "x", "j", "y", "c").collect()
        want = counts.contingency(dense, None if j is None else f"f{j}").select("feature", "x", "j", "y", "c").collect()
        assert sorted(map(lambda r: str(tuple(r)), got)) == sorted(map(lambda r: str(tuple(r)), want))
    assert greedy.select(ds, 3, "jmi").names == [f"t{n[1:]}" for n in greedy.select(dense, 3, "jmi").names]


def test_blocks_round_trip_and_partial_histograms(spark):
    ds = workloads.lines(spark, "/root/testdata/sf0.001").only(["qty", "disc"])
    back = layout.from_feature_blocks(layout.to_feature_blocks(ds), ds.features)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, ds.columns().select("qty", "disc", "y").collect()))
    parts = layout.partial_histograms(layout.to_feature_blocks(ds, 2)).collect()
    assert max(r["partitions"] for r in parts) <= 2


def test_planner_and_bins(spark):
    ds = workloads.lines(spark, "/root/testdata/sf0.001")
    assert planner.choose(ds) == planner.Strategy("packed", "driver")
    assert planner.choose(ds, "frame") == planner.Strategy("explode", "frame")
    assert planner.choose(Dataset(ds.df, list(GATE) * 60), "frame").counting == "arrow"
    wide = Dataset(spark.range(10).selectExpr("cast(id * 1000 as int) AS a", "0 AS y"), ["a"])
    with pytest.raises(ValueError):
        wide.check()
    assert layout.feature_partitions(10) == 10 and layout.feature_partitions(10, 50) == 20


def test_encoders(spark):
    rows = spark.createDataFrame([(0.0,), (5.0,), (10.0,), (None,)], "v double")
    got = [r[0] for r in rows.select(encode.with_invalid(encode.equal_width(F.col("v"), 0, 10, 4), F.col("v"), 4)).collect()]
    assert got == [0, 2, 3, 4]
    words = spark.createDataFrame([(["a", "b", "c"],), (["a"],), ([],)], "w array<string>")
    assert [r[0] for r in words.select(encode.ngrams(F.col("w"), 2)).collect()] == [["a b", "b c"], [], []]
    assert [r[0] for r in words.select(encode.ngrams(F.col("w"), 3)).collect()] == [["a b c"], [], []]


def test_auc_by_hand_and_against_spark(spark):
    from pyspark.ml.evaluation import BinaryClassificationEvaluator

    of = lambda rows: metrics.auc(spark.createDataFrame(rows, "score double, y int")).first()["auc"]
    assert of([(0.1, 0), (0.2, 0), (0.8, 1)]) == 1
    assert of([(0.9, 0), (0.2, 1)]) == 0
    assert of([(0.5, 0), (0.5, 1)]) == 0.5
    rng = np.random.default_rng(1)
    rows = [(float(round(s, 2)), int(rng.random() < s)) for s in rng.random(400)]
    df = spark.createDataFrame(rows, "score double, y int")
    want = BinaryClassificationEvaluator(rawPredictionCol="score", labelCol="y").evaluate(df)
    assert metrics.auc(df).first()["auc"] == pytest.approx(want, abs=1e-9)


def test_sampling(spark):
    df = spark.range(1000).selectExpr("id", "cast(id % 10 = 0 as int) AS y")
    train, test = sampling.holdout(df, F.col("id"))
    assert train.count() + test.count() == 1000 and train.join(test, "id").count() == 0
    n = {r["y"]: r["count"] for r in sampling.random_oversample(df, "y", key=F.col("id")).groupBy("y").count().collect()}
    assert n[0] == 900 and n[1] == 900


def test_naive_bayes_recovers_the_class(spark):
    ds = workloads.lines(spark, "/root/testdata/sf0.001")
    train, test = sampling.holdout(ds.df, F.col("l_orderkey"))
    area = metrics.auc(models.CategoricalNB(["disc", "tax", "qty"]).fit(train).score(test, [])).first()["auc"]
    assert area > 0.95


def test_estimator(spark, tmp_path):
    from pyspark.ml.feature import VectorAssembler

    from featsift.operators.estimator import InfoSelector, InfoSelectorModel

    rows = workloads.lines(spark, "/root/testdata/sf0.001").df
    rows = VectorAssembler(inputCols=list(GATE), outputCol="features").transform(rows).withColumnRenamed("y", "label")
    model = InfoSelector(k=3, criterion="mrmr").fit(rows)
    assert len(model.getOrDefault("indices")) == 3 and model.transform(rows).first()["selected"].size == 3
    model.save(str(tmp_path / "m"))
    assert InfoSelectorModel.load(str(tmp_path / "m")).getOrDefault("indices") == model.getOrDefault("indices")


def test_extrapolation_of_published_times():
    points = [(1, 450.0), (5, 2839.72)]
    assert metrics.extrapolate_linear(points, 40) == pytest.approx(23749.77)
    assert metrics.extrapolate_linear(points, 80) == pytest.approx(47646.97)
    assert metrics.kendall_distance("abc", "cba") == 3 and metrics.overlap("abc", "abd") == pytest.approx(2 / 3)


def test_round_has_one_exchange_and_reads_only_its_columns(spark):
    ds = workloads.lines(spark, "/root/testdata/sf0.001").only(["disc", "tax"])
    cells = counts.contingency(ds, "disc")
    assert metrics.plan_costs(cells) == {"exchanges": 1, "broadcasts": 0, "python": 0}
    text = cells._jdf.queryExecution().executedPlan().toString()
    assert "l_shipdate" not in text.split("ReadSchema")[1]


def test_entry_module():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())


def test_packed_counts_in_sets_of_columns(spark, monkeypatch):
    """More features than one column of a block holds, counted in sets within a small budget, with nulls and weights."""
    from featsift.operators import packed

    monkeypatch.setattr(packed, "COUNT_BYTES", 2000)
    monkeypatch.setattr(packed, "PART_BYTES", 500)
    monkeypatch.setattr(packed, "GROUP", 4)
    rng = np.random.default_rng(11)
    names = [f"f{i}" for i in range(11)]
    codes = rng.integers(0, rng.integers(2, 7, 11), (300, 11))
    rows = [tuple(None if rng.random() < 0.1 else int(v) for v in r) + (int(rng.integers(3)), int(rng.integers(1, 4))) for r in codes]
    df = spark.createDataFrame(rows, ", ".join(f"{n} int" for n in names) + ", y int, w long").repartition(3)
    for weight in (None, "w"):
        ds = Dataset(df, names, weight=weight)
        engine = packed.DenseEngine(ds)
        assert len(packed.column_sets([s * engine.sizes[5] * engine.classes for s in engine.sizes], 2000)) > 2
        for j in (None, 5):
            want = sorted(map(str, counts.contingency(ds, j and names[j], "explode").select("feature", "x", "j", "y", "c").collect()))
            assert sorted(map(str, engine.cells(j).select("feature", "x", "j", "y", "c").collect())) == want
            assert sorted(map(str, counts.contingency(ds, j and names[j], "arrow").select("feature", "x", "j", "y", "c").collect())) == want
        red = {r["feature"]: (r["mi"], r["cmi"]) for r in relevance.redundancy(ds, "f5", "explode").collect()}
        ids, mi, cmi = engine.pair(5, [9, 2])
        assert ids.tolist() == [2, 9] and [(a, b) for a, b in zip(mi, cmi)] == [pytest.approx(red[2]), pytest.approx(red[9])]
        want = greedy.select(ds, 4, "jmi", strategy="explode").steps
        assert greedy.select(ds, 4, "jmi").steps == [dict(s, score=pytest.approx(s["score"]), rel=pytest.approx(s["rel"])) for s in want]
        engine.release()


def test_packed_refuses_what_would_not_fit(spark, monkeypatch):
    from featsift.operators import packed

    wide = Dataset(spark.range(10).selectExpr("cast(id * 1000 as int) AS a", "0 AS y"), ["a"])
    monkeypatch.setattr(packed, "MAX_CELLS", 1000)
    with pytest.raises(ValueError):
        packed.DenseEngine(wide)
    none = Dataset(spark.createDataFrame([], "a int, b int, y int"), ["a", "b"])
    assert greedy.select(none, 1).names == ["a"]


def test_sparse_engine_with_codes_and_classes(spark, monkeypatch):
    """Several codes and classes, rows split over blocks, features without a row in common."""
    from featsift.operators import packed
    from featsift.plans.dataset import SparseDataset

    monkeypatch.setattr(packed, "GATHERED", 50)
    monkeypatch.setattr(packed, "BLOCK_ENTRIES", 20)
    rng = np.random.default_rng(6)
    rows = [(i, 10 * f, int(rng.integers(1, 4))) for i in range(90) for f in range(7) if rng.random() < 0.25 and (f != 6 or i > 80)]
    classes = spark.createDataFrame([(i, int(rng.integers(0, 3))) for i in range(90)], "row_id long, y int")
    posts = spark.createDataFrame(rows, "row_id long, feature long, code int").join(classes, "row_id")
    ds = SparseDataset(posts, classes, spark.createDataFrame([(10 * f, f"t{f}") for f in range(7)], "feature long, name string"))
    engine = packed.SparseEngine(ds)
    ids, names, rel = engine.relevance()
    assert names == [f"t{f}" for f in range(7)]
    want = {r["feature"]: r["rel"] for r in relevance.relevance(ds).collect()}
    assert dict(zip(ids.tolist(), rel)) == pytest.approx(want)
    for j in (20, 60):
        want = {r["feature"]: (r["mi"], r["cmi"]) for r in relevance.redundancy(ds, j).collect()}
        ids, mi, cmi = engine.pair(j)
        assert dict(zip(ids.tolist(), mi)) == pytest.approx({k: v[0] for k, v in want.items()}, abs=1e-9)
        assert dict(zip(ids.tolist(), cmi)) == pytest.approx({k: v[1] for k, v in want.items()}, abs=1e-9)
        met = sorted(map(tuple, engine.met(j).select("feature", "x", "j", "y", "c").collect()))
        assert met == sorted(map(tuple, sparse.met_cells(ds, j).select("feature", "x", "j", "y", "c").collect()))
    engine.release()
    assert greedy.select(ds, 4, "cmim").names == greedy.select(ds, 4, "cmim", strategy="sparse").names == greedy.select(ds, 4, "cmim", state="frame").names


def test_log_of_other_data_is_refused(spark, tmp_path):
    rows = [(i % 2, i % 3, i % 2) for i in range(60)]
    x = Dataset(spark.createDataFrame(rows, "a int, b int, y int"), ["a", "b"])
    y = Dataset(spark.createDataFrame([(r[0], r[1], r[1] % 2) for r in rows], "a int, b int, y int"), ["a", "b"])
    log = str(tmp_path / "log")
    first = greedy.select(x, 1, resume=log)
    with pytest.raises(ValueError):
        greedy.select(y, 1, resume=log)
    again = greedy.select(Dataset(x.df.repartition(3), ["a", "b"]), 2, resume=log)  # the order of rows doesn't matter
    assert again.names[:1] == first.names == ["a"]
    assert greedy.select(x, 2, resume=log, state="frame").names == again.names
    sparse_x = layout.sparsified(x)[0]
    with pytest.raises(ValueError):
        greedy.select(sparse_x, 1, resume=log)
    other = str(tmp_path / "sparse")
    assert greedy.select(sparse_x, 1, resume=other).names == greedy.select(sparse_x, 2, resume=other).names[:1]


def test_vectors_of_train_and_test_line_up(spark):
    train = spark.createDataFrame([(i % 4, i % 3, i % 2) for i in range(48)], "a int, b int, y int")
    test = spark.createDataFrame([(0, 2, 0), (7, None, 1), (3, 0, 1)], "a int, b int, y int")  # unseen, null and missing codes
    encode_ = models.OneHot(train, ["a", "b"])
    assert {r["v"].size for rows in (train, test) for r in encode_(rows).collect()} == {5 + 4}
    assert [r["v"].toArray().argmax() for r in encode_(test).collect()] == [0, 4, 3]
    for fit in (models.naive_bayes, models.svm):
        assert models.scored(fit(encode_(train)), encode_(test)).count() == 3


def test_sgd_against_numpy(spark):
    """Full-batch subgradient steps of the hinge loss, step / sqrt(t), with shrinking weights."""
    rng = np.random.default_rng(2)
    x = rng.standard_normal((80, 3))
    y = (x @ [1.0, -2.0, 0.5] > 0).astype(int)
    from pyspark.ml.linalg import Vectors

    train = spark.createDataFrame([(Vectors.dense(v), float(c)) for v, c in zip(x.tolist(), y.tolist())], ["v", "y"])
    model = models.svm(train, impl="sgd", iters=30, step=1.0, reg=0.1)
    w, sign = np.zeros(3), 2 * y - 1
    for t in range(1, 31):
        wrong = sign * (x @ w) < 1
        slope = -(sign[wrong, None] * x[wrong]).sum(0) / len(x)
        w = w * (1 - 0.1 / np.sqrt(t)) - slope / np.sqrt(t)
    assert np.allclose(np.array(model.weights), w, atol=1e-6)
    assert metrics.auc(models.scored(model, train)).first()["auc"] > 0.95


def test_numbering_and_bins_over_many_ranges(spark):
    from featsift.plans.storage import looked_up, numbered

    rows = spark.range(1000).selectExpr("cast(id * 7919 % 1000 as long) AS v", "id").repartition(5)
    got = numbered(rows, ["v"], "at").collect()
    assert sorted((r["v"], r["at"]) for r in got) == [(i, i) for i in range(1000)]
    assert numbered(rows.limit(0), ["v"], "at").count() == 0
    binned = encode.ntile_bins(rows.where("v < 103"), "v", 10, ["id"])
    assert sorted(r["count"] for r in binned.groupBy("v_bin").count().collect()) == [10] * 7 + [11] * 3
    keys = spark.createDataFrame([("hot", 1)] * 50 + [("cold", 2), (None, 3), ("none", 4)], "k string, i int")
    found = spark.createDataFrame([("hot", 10, 50), ("cold", 20, 1), (None, 30, 1)], "k string, v int, n long")
    assert sorted((r["i"], r["v"]) for r in looked_up(keys, found, ["k"], ["v"], "n", 53, nulls=True).distinct().collect() if r["i"] < 4) == [(1, 10), (2, 20), (3, 30)]
    plain = looked_up(keys, found, ["k"], ["v"], "n", 53)
    assert plain.count() == 53 and plain.where("i IN (3, 4) AND v IS NULL").count() == 2


def test_complete_streams_leave_the_driver(spark, sf_dir):
    from featsift import catalogue

    found = catalogue.QUERIES["stream_window_counts"](spark, sf_dir)
    assert found.inputFiles()  # a table in memory has none
    one = catalogue.QUERIES["stream_session_counts"](spark, sf_dir).first()
    assert one["events"] == spark.read.parquet(f"{sf_dir}/events.parquet").count() and one["sessions"] <= one["events"]


def test_one_core_codes_take_a_byte(spark, monkeypatch):
    ds = workloads.lines(spark, SF01)
    want = greedy.select(ds, 3, "mrmr").steps
    held, one_core = [], baselines.one_core
    monkeypatch.setattr(baselines, "one_core", lambda columns, *a, **b: held.append(columns) or one_core(columns, *a, **b))
    got = baselines.sequential(ds, 3, "mrmr")
    assert [(s["name"], round(s["score"], 9)) for s in got] == [(s["name"], round(s["score"], 9)) for s in want]
    assert sum(c.nbytes for piece in held[0].pieces for c in piece) == 11 * ds.n
    with pytest.raises(MemoryError):
        baselines.sequential(ds, 3, "mrmr", max_rows=10)


def test_table_function_takes_grouped_rows(spark):
    from featsift.functions import udf

    udf.register_functions(spark)
    rows = workloads.lines(spark, "/root/testdata/sf0.001").df.select("qty_band", "disc_hi", "tax", "rf", "y")
    rows.createOrReplaceTempView("fs_plain")
    rows.groupBy(*rows.columns).count().createOrReplaceTempView("fs_grouped")
    call = "SELECT step, name, round(score, 9) AS score FROM select_features(TABLE({}) PARTITION BY (rf), 'y', 3, 'mrmr'{})"
    plain, grouped = (sorted(map(tuple, spark.sql(call.format(*x)).collect())) for x in (("fs_plain", ""), ("fs_grouped", ", 'count'")))
    assert plain == grouped and len(plain) == 9


@pytest.mark.parametrize("name", ["criteria_registered", "extrapolated_times", "random_features", "rel_recursive_cte"])
def test_results_follow_from_a_table(spark, sf_dir, name):
    """Against the SQL, on two tables with different results."""
    import duckdb

    from featsift import catalogue

    found = []
    for path in (sf_dir, SF01):
        con = duckdb.connect()
        for t in ("lineitem", "orders", "customer", "documents", "labels"):
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path}/{t}.parquet'")
        got = sorted(map(tuple, catalogue.QUERIES[name](spark, path).collect()))
        assert got == sorted(con.sql(catalogue.ORACLE_SQL[name]).fetchall())
        found.append(got)
    assert found[0] and found[0] != found[1]


@pytest.mark.parametrize("local", [0, 1 << 20])
def test_sgd_of_grouped_rows(spark, monkeypatch, local):
    """Weighted rows give what the library gives on single ones, on the driver and by jobs."""
    from pyspark.mllib.classification import SVMWithSGD
    from pyspark.mllib.regression import LabeledPoint

    monkeypatch.setattr(models, "LOCAL_BYTES", local)
    rows = workloads.lines(spark, "/root/testdata/sf0.001", "noisy").df.where("l_orderkey < 300")
    names = ["disc", "tax"]
    encode_ = models.OneHot(rows, names)
    one = encode_(models.grouped(rows, names))
    assert one.count() < rows.count() and one.agg(F.sum("weight")).first()[0] == rows.count()
    model = models.svm(one, impl="sgd", iters=20)
    points = encode_(rows).rdd.map(lambda r: LabeledPoint(r["y"], r["v"].toArray()))
    want = SVMWithSGD.train(points, iterations=20, step=1.0, regParam=1.0)
    assert np.allclose(model.weights, want.weights.toArray(), atol=1e-9)
    single = models.scored(model, encode_(rows)).withColumn("score", F.round("score", 10))
    grouped = models.scored(model, one).withColumn("score", F.round("score", 10))
    assert metrics.auc(grouped, weight="weight").first()["auc"] == pytest.approx(metrics.auc(single).first()["auc"])


@pytest.mark.parametrize("criterion", ["mrmr", "jmi", "cmim", "mim"])
def test_all_pairs_are_counted_in_one_job(spark, monkeypatch, criterion):
    """Where the rounds would count no fewer cells; with nulls, weights and more features than one column of a block holds."""
    from featsift.operators import packed

    monkeypatch.setattr(packed, "GROUP", 4)
    monkeypatch.setattr(packed, "PART_BYTES", 500)
    rng = np.random.default_rng(5)
    names = [f"f{i}" for i in range(9)]
    codes = rng.integers(0, rng.integers(1, 6, 9), (200, 9))
    rows = [tuple(None if rng.random() < 0.1 else int(v) for v in r) + (int(rng.integers(3)), int(rng.integers(1, 4))) for r in codes]
    df = spark.createDataFrame(rows, ", ".join(f"{n} int" for n in names) + ", y int, w long").repartition(3)
    jobs, count = [], packed.DenseEngine.information
    monkeypatch.setattr(packed.DenseEngine, "information", lambda self, *a: jobs.append(1) or count(self, *a))
    for weight in (None, "w"):
        ds = Dataset(df, names, weight=weight)
        want = greedy.select(ds, 9, criterion, strategy="explode").steps
        want = [dict(s, score=pytest.approx(s["score"], abs=1e-11), rel=pytest.approx(s["rel"], abs=1e-11)) for s in want]
        jobs.clear()
        assert greedy.select(ds, 9, criterion).steps == want
        assert len(jobs) == (1 if criterion == "mim" else 2)
        # of few features chosen, pairs are counted round by round
        jobs.clear()
        assert greedy.select(ds, 4, criterion).steps == want[:4]
        assert len(jobs) == (1 if criterion == "mim" else 4)
        # so they are where the tables of all pairs would be too large
        jobs.clear()
        with monkeypatch.context() as m:
            m.setattr(packed, "COUNT_BYTES", 3000)
            assert greedy.select(ds, 9, criterion).steps == want
        assert len(jobs) == (1 if criterion == "mim" else 9)
    none = Dataset(spark.createDataFrame([], "a int, b int, c int, y int"), ["a", "b", "c"])
    assert greedy.select(none, 3, criterion).names == ["a", "b", "c"]


def test_times_have_what_comes_before_the_first_round(spark, sf_dir, monkeypatch):
    import time

    from featsift import catalogue

    def slow(ds, k, criterion):
        time.sleep(0.2)
        return greedy.Selection(spark, [{}] * k, [0.0] * (k - 1) + [0.1])

    monkeypatch.setattr(greedy, "select", slow)
    found = catalogue.selection_times(spark, sf_dir).collect()
    assert len(found) == 17 and all(r["seconds"] > 0.05 for r in found)
