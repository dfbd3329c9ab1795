"""Algebra, limits, equivalences, costs, edges and restrictions of the clustering engine."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from landmark_kkm import dataset, workloads
from landmark_kkm.functions import columns as C
from landmark_kkm.functions import kernels as K
from landmark_kkm.functions.payloads import Dense, Objects, Sparse, from_arrow
from landmark_kkm.operators import baselines, exact, measures, relational, shared, vectors
from landmark_kkm.operators.cluster import ClusterModel, cluster, costs, lloyd
from landmark_kkm.operators.coefficients import Nystrom, NystromEnsemble, StableProjection, block_bytes, centred, fit_on_executors, reconstruct, to_frame
from landmark_kkm.operators.embed import embed
from landmark_kkm.operators.estimator import KernelKMeansModel, ScalableKernelKMeans
from landmark_kkm.operators.landmarks import Landmarks, collect_landmarks, sample_landmarks
from landmark_kkm.operators.ledger import CostLedger, exact_bytes, iteration_bytes
from landmark_kkm.plans import choices
from landmark_kkm.queries import QUERIES
from landmark_kkm.sources import features, synthetic
from landmark_kkm.sources.tables import from_libsvm, read, register_views, table, to_ml_vector, write
from landmark_kkm.streaming import streams


def numpy_rows(df, column="y"):
    rows = df.orderBy("id").select(column).collect()
    return np.array([r[0] for r in rows], dtype=float)


@pytest.fixture(scope="module")
def text(spark, sf_dir):
    ds = features.text_grams(spark, sf_dir).cache()
    ds.count()
    return ds


@pytest.fixture(scope="module")
def dense(spark, sf_dir):
    ds = features.dense(spark, sf_dir).cache()
    ds.count()
    return ds


@pytest.fixture(scope="module")
def rings(spark):
    ds = synthetic.planted(spark, "rings", 1000, noise=0.15).cache()
    ds.count()
    return ds


def best_of(y, k, discrepancy, seeds=5):
    return min((cluster(y, k, discrepancy, seed=s, tol=0.0) for s in range(seeds)), key=lambda m: m.history[-1]["cost"])


def test_kernels_by_hand():
    a, b = Dense(np.array([[1.0, 0.0], [0.0, 2.0]])), Dense(np.array([[1.0, 1.0]]))
    assert np.allclose(K.Linear().matrix(a, b), [[1], [2]])
    assert np.allclose(K.Rbf(2.0).matrix(a, b), np.exp(-np.array([[1], [2]]) / 8))
    assert np.allclose(K.Laplacian(2.0).matrix(a, b), np.exp(-np.array([[1], [2]]) / 2))
    assert np.allclose(K.Polynomial(3, 1).matrix(a, b), [[8], [27]])
    assert np.allclose(K.cosine().matrix(a, b), 1 / np.sqrt(2))
    sets = Objects([["a", "b"], [], None])
    assert np.allclose(K.Jaccard().matrix(sets, Objects([["b", "c"]])), [[1 / 3], [0], [0]])
    maps = Objects([{"a": 1.0, "b": 5.0}, {}])
    assert np.allclose(K.HistogramIntersection().matrix(maps, Objects([{"b": 2.0, "c": 1.0}])), [[2], [0]])
    assert np.allclose(K.Spectrum(2).matrix(Objects(["abab", None]), Objects(["ab"])), [[2], [0]])
    assert np.allclose(K.Custom(lambda x, z: x @ z.T).matrix(a, b), [[1], [2]])
    assert K.LocalRbf().matrix(Dense(np.array([[0.0, 2.0]])), Dense(np.array([[1.0, 4.0]])))[0, 0] == pytest.approx(np.exp(-1 / 8))
    given = Objects([[(-1, 7.0), (7, 2.0), (8, 0.5)], [(-1, 8.0), (7, 0.5), (8, 3.0)]])
    assert np.allclose(K.Precomputed().matrix(given, given), [[2, 0.5], [0.5, 3]]) and np.allclose(K.Precomputed().diagonal(given), [2, 3])
    for kernel in (K.Rbf(1.0), K.Linear(), K.Polynomial(), K.Neural(), K.cosine(), K.Laplacian(1.0)):
        assert np.allclose(kernel.diagonal(a), np.diag(kernel.matrix(a, a)))


def test_sparse_equals_dense():
    rng = np.random.default_rng(0)
    x = rng.random((60, 40)) * (rng.random((60, 40)) < 0.2)
    at = [np.flatnonzero(r) for r in x]
    sparse = Sparse(40, np.append(0, np.cumsum([len(a) for a in at])), np.concatenate(at), np.concatenate([r[a] for r, a in zip(x, at)]))
    part = sparse.take(np.arange(3, 20))
    assert np.allclose(sparse.dot(part), x @ x[3:20].T) and np.allclose(sparse.norms(), (x * x).sum(1))
    assert np.allclose(K.Rbf(1.0).matrix(sparse, part), K.Rbf(1.0).matrix(Dense(x), Dense(x[3:20])))


def test_column_twins_equal_numpy(spark, dense):
    lm = collect_landmarks(sample_landmarks(dense, 3))
    z = F.array(*[F.lit(float(v)) for v in lm.rows.rows[0]])
    x = numpy_rows(dense, "x")
    one = Dense(lm.rows.rows[:1])
    for column, kernel in ((C.rbf(F.col("x"), z, 1.0), K.Rbf(1.0)), (C.laplacian(F.col("x"), z, 2.0), K.Laplacian(2.0)), (C.polynomial(F.col("x"), z), K.Polynomial()), (C.neural(F.col("x"), z), K.Neural()), (C.cosine(F.col("x"), z), K.cosine())):
        assert np.allclose(numpy_rows(dense.select("id", column.alias("y"))), kernel.matrix(Dense(x), one)[:, 0])
    assert np.allclose(np.linalg.norm(numpy_rows(dense.select("id", C.unit(C.scaled(F.col("x"), 7.0)).alias("y"))), axis=1), 1)


def test_landmarks_do_not_depend_on_partitions(spark, dense):
    ids = [r.id for r in sample_landmarks(dense, 3).select("id").collect()]
    assert sorted(ids) == [16, 238, 322]
    for parts in (1, 7, 64):
        assert sorted(r.id for r in sample_landmarks(dense.repartition(parts), 3).collect()) == [16, 238, 322]
    sizes = [sample_landmarks(dense, 100, "bernoulli", seed=s).count() for s in range(5)]
    assert 60 < np.mean(sizes) < 140 and len(set(sizes)) > 1
    with pytest.raises(ValueError):
        sample_landmarks(dense, 0)


def test_two_landmark_nystrom_reference_value(dense):
    y = embed(dense.filter("id = 0"), Nystrom(2).fit(collect_landmarks(sample_landmarks(dense, 2)), K.Rbf(1.0)), K.Rbf(1.0), kind="double").first().y
    assert np.allclose(np.abs(y), [0.43947188, 0.05723860], atol=1e-7)


def test_algebra(dense):
    lm = collect_landmarks(sample_landmarks(dense, 80))
    A = K.Rbf(1.0).matrix(lm.rows, lm.rows)
    R = Nystrom(1000).fit(lm, K.Rbf(1.0))[0].R
    assert np.abs(R @ A @ R.T - np.eye(len(R))).max() < 1e-8
    assert np.abs(reconstruct((R @ A).T) - A).max() < 1e-8
    E, dropped = StableProjection().inverse_root(A)
    P = E @ centred(A) @ E
    assert np.abs(P @ P - P).max() < 1e-8 and dropped == 1 and np.abs(E @ np.ones(len(E))).max() < 1e-8
    blocks = StableProjection(50).fit(lm, K.Rbf(1.0))
    scaled = StableProjection(50, scale="distance").fit(lm, K.Rbf(1.0))
    assert np.allclose(scaled[0].R, blocks[0].R * StableProjection(50).beta(blocks))


def test_full_rank_embedding_gives_exact_distances_and_labels(spark, dense):
    ds = dense.filter("id < 120")
    lm = collect_landmarks(ds.select("id", "x"))
    kernel = K.Rbf(1.0)
    y = embed(ds, Nystrom(120).fit(lm, kernel), kernel, kind="double").cache()
    labels = np.arange(120) % 4
    new, d2 = exact.step(kernel.matrix(lm.rows, lm.rows), np.ones(120), labels, 4)
    Y = Nystrom(120).fit(lm, kernel)[0].apply(lm.rows, kernel)
    centroids = np.array([Y[labels == c].mean(0) for c in range(4)])
    assert np.allclose(costs(Y, centroids, "l2"), d2, atol=1e-6)
    by_exact = exact.exact_kkm(ds.select("id", "x"), kernel, 4, init=labels, max_iter=4)
    model = cluster(y, 4, "l2", init=centroids, max_iter=3)
    found = {r.id: r.cluster for r in model.transform(y).collect()}
    assert [found[i] for i in by_exact.ids] == by_exact.labels.tolist()
    again = exact.exact_kkm(ds.select("id", "x"), kernel, 4, init=labels, max_iter=4, kernel_storage="recompute")
    assert (again.labels == by_exact.labels).all()
    assert all(a["cost"] >= b["cost"] - 1e-9 for a, b in zip(by_exact.history, by_exact.history[1:]))


def test_linear_kernel_is_lloyd(dense):
    ds = dense.filter("id < 150").select("id", "x")
    lm = collect_landmarks(ds)
    labels = np.arange(150) % 3
    by_kernel = exact.exact_kkm(ds, K.Linear(), 3, init=labels, max_iter=3)
    centroids = np.array([lm.rows.rows[labels == c].mean(0) for c in range(3)])
    found = {r.id: r.cluster for r in lloyd(ds, 3, init=centroids, max_iter=2).transform(ds.withColumnRenamed("x", "y")).collect()}
    assert [found[i] for i in by_kernel.ids] == by_kernel.labels.tolist()


def test_span_equals_full_rank_nystrom(dense):
    lm = collect_landmarks(sample_landmarks(dense, 60))
    y = embed(dense, Nystrom(60).fit(lm, K.Rbf(1.0)), K.Rbf(1.0), kind="double")
    a = cluster(y, 4, "l2", init="random", max_iter=4).transform(y).select("id", "cluster")
    ky, model = baselines.span_kkm(dense, K.Rbf(1.0), 4, 60, max_iter=4, landmarks=lm, init="random")
    assert a.join(model.transform(ky).select("id", F.col("cluster").alias("o")), "id").filter("cluster <> o").count() == 0


def test_modes_combiner_and_partitions_agree(spark, dense):
    lm = collect_landmarks(sample_landmarks(dense, 80))
    blocks = NystromEnsemble(40, 4).fit(lm, K.Rbf(1.0))
    ys = [numpy_rows(embed(dense, blocks, K.Rbf(1.0), m, kind="double")) for m in ("fused", "rounds", "staged")]
    assert np.allclose(ys[0], ys[1]) and np.allclose(ys[0], ys[2])
    y = embed(dense, blocks, K.Rbf(1.0), kind="double").cache()
    runs = [cluster(y.repartition(p), 3, "l2", init="random", max_iter=3).centroids for p in (1, 7, 64)]
    runs.append(cluster(y, 3, "l2", init="random", max_iter=3, combine=False).centroids)
    doubled = y.unionByName(y.withColumn("id", F.col("id") + 10_000))
    runs.append(cluster(doubled, 3, "l2", init=cluster(y, 3, "l2", init="random", max_iter=0).centroids, max_iter=3).centroids)
    assert all(np.allclose(runs[0], r, atol=1e-9) for r in runs[1:])
    weighted = cluster(y.withColumn("w", F.lit(2.0)), 3, "l2", init="random", max_iter=3, weight_col="w")
    assert np.allclose(runs[0], weighted.centroids, atol=1e-9) and weighted.sizes.sum() == 1000
    assert cluster(y, 3, init="partition", max_iter=2).sizes.sum() == 500


def test_two_level_merge_is_the_same(dense, monkeypatch):
    from landmark_kkm.operators import vectors

    y = dense.withColumnRenamed("x", "y").repartition(32)
    one = cluster(y, 3, init="random", max_iter=2).centroids
    monkeypatch.setattr(vectors, "TWO_LEVELS", 4)
    assert np.allclose(one, cluster(y, 3, init="random", max_iter=2).centroids)


def test_executor_fit_equals_driver_fit(spark, dense):
    lm = collect_landmarks(sample_landmarks(dense, 40))
    there = fit_on_executors(spark, Nystrom(10), lm, K.Rbf(1.0), 2)
    here = NystromEnsemble(20, 2).fit(lm, K.Rbf(1.0))
    assert all(np.allclose(a.R, b.R, atol=1e-8) for a, b in zip(there, here))
    assert to_frame(spark, here).count() == 20 and len(block_bytes(here)) == 2
    stable = StableProjection(15)
    assert np.allclose(fit_on_executors(spark, stable, lm, K.Rbf(1.0))[0].R, stable.fit(lm, K.Rbf(1.0))[0].R, atol=1e-6)
    with pytest.raises(ValueError):
        fit_on_executors(spark, stable, lm, K.Rbf(1.0), 2)


def test_local_scale_leaves_out_the_row_itself_and_its_copies():
    x = np.random.default_rng(3).normal(size=(20, 8)) * 1000
    x[1] = x[0]
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    d[d == 0] = np.inf
    assert np.allclose(K.local_scales(Dense(x), Dense(x), 2), np.sort(d, axis=1)[:, 1])


def test_late_rows_are_counted_and_texts_without_words_are_kept(spark, sf_dir, tmp_path):
    rows = lambda *at: spark.createDataFrame([(i, t) for i, t in at], "k long, t string").withColumn("t", F.col("t").cast("timestamp"))
    parts = [rows((1, "2024-01-10 00:00:00")), rows((2, "2024-01-09 23:30:00")), rows((3, "2024-01-01 00:00:00"), (4, "2024-01-02 00:00:00"), (1, "2024-01-09 23:59:00"))]
    found, dropped = streams.run_reported(streams.deduplicated(streams.replayed(parts), "t", ["k"], "1 hour"))
    assert sorted(r.k for r in found.collect()) == [1, 2] and dropped == 2
    docs = spark.createDataFrame([(1, "one two two", "en", "a"), (2, "  ", "en", "b"), (3, None, None, "c")], "doc_id long, text string, lang string, source string")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    sparse = {r.id: r for r in features.text_sparse(spark, str(tmp_path)).collect()}
    assert {i: len(r.x.idx) for i, r in sparse.items()} == {1: 2, 2: 0, 3: 0} and sparse[3].cls is None


def test_embeddings_separate_rings_and_lloyd_does_not(rings):
    kernel, lm = K.Rbf(1.0), collect_landmarks(sample_landmarks(rings, 100))
    for family in (Nystrom(200), StableProjection(200)):
        y = embed(rings, family.fit(lm, kernel), kernel).cache()
        assert measures.nmi(best_of(y, 2, family.discrepancy).transform(y)).first().nmi >= 0.95
    raw = rings.withColumnRenamed("x", "y")
    assert measures.nmi(best_of(raw, 2, "l2").transform(raw)).first().nmi <= 0.05


def test_blobs(spark):
    ds = synthetic.planted(spark, "blobs", 1000, clusters=10, dimensions=16, noise=1.0, seed=3).cache()
    kernel = K.Rbf(K.self_tuned_sigma(collect_landmarks(sample_landmarks(ds, 200)).rows) * 2)
    lm = collect_landmarks(sample_landmarks(ds, 100))
    for family in (Nystrom(100), StableProjection(300)):
        y = embed(ds, family.fit(lm, kernel), kernel).cache()
        assert measures.nmi(best_of(y, 10, family.discrepancy, 3).transform(y)).first().nmi >= 0.9


def test_assignments_agree_with_exact_and_beta_is_closed_form(text):
    rows = collect_landmarks(text.select("id", "x"))
    kernel = K.Rbf(K.self_tuned_sigma(rows.rows))
    names = {r.id: r.cls for r in text.select("id", "cls").collect()}
    classes = sorted(set(names.values()))
    labels = np.array([classes.index(names[i]) for i in rows.ids])
    report = {n: workloads.agreement_with_exact(text, kernel, 4, 100, f, labels) for n, f in (("nystrom", Nystrom(1000)), ("stable", StableProjection(400)), ("eigen", StableProjection(400, root="eigen")))}
    assert report["nystrom"]["agreement"] >= 0.97 and report["stable"]["agreement"] >= 0.95
    assert report["eigen"]["agreement"] < report["stable"]["agreement"]
    assert report["stable"]["beta_ratio"] == pytest.approx(1, abs=0.25)
    lm = collect_landmarks(sample_landmarks(text.select("id", "x"), 100))
    few = measures.kernel_error(rows, Nystrom(20).fit(lm, kernel), kernel)
    assert measures.kernel_error(rows, Nystrom(100).fit(lm, kernel), kernel) < few


def test_chance_level_reference(dense):
    rows = dense.select(F.pmod("id", F.lit(10)).alias("cluster"), "cls")
    assert measures.nmi(rows).first().nmi == pytest.approx(0.035765, abs=1e-6)


def test_measures_by_hand(spark):
    df = spark.createDataFrame([(0, "a"), (0, "a"), (1, "b"), (1, "a"), (None, "a"), (1, None)], "cluster int, cls string")
    assert measures.purity(df).first().purity == pytest.approx(0.75)
    assert measures.nmi(spark.createDataFrame([(0, "a"), (0, "a")], df.schema)).first().nmi == 1.0
    assert measures.nmi(spark.createDataFrame([(0, "a"), (1, "a")], df.schema)).first().nmi == 0.0
    assert measures.nmi(spark.createDataFrame([], df.schema)).count() == 0
    assert measures.nmi(spark.createDataFrame([(0, "a"), (1, "b")], df.schema)).first().nmi == pytest.approx(1)
    assert measures.ari(spark.createDataFrame([(0, "a"), (1, "b"), (0, "a")], df.schema)).first().ari == pytest.approx(1)
    assert {(r.cluster, r.cls, r.n) for r in measures.majority_class(df).collect()} == {(0, "a", 2), (1, "a", 1)}


def test_t_test_values(spark):
    assert measures.t_test(10, 2, 5, 8, 2, 5, True)[0] == pytest.approx(1.5811388)
    assert measures.t_test(2.228138852, 1, 10**9, 0, 1, 10**9)[2] == pytest.approx(0, abs=1e-6)
    assert measures.incomplete_beta(5, 0.5, 10 / (10 + 2.228138852**2)) == pytest.approx(0.05, abs=1e-6)
    assert measures.incomplete_beta(2.5, 0.5, 5 / (5 + 2.570581836**2)) == pytest.approx(0.05, abs=1e-6)
    runs = [("w", "a", 50, 0.5 + i / 100) for i in range(5)] + [("w", "b", 50, 0.505 + i / 100) for i in range(5)] + [("w", "c", 50, 0.1 + i / 100) for i in range(5)]
    best = {r.method: r.best for r in measures.best_by_ttest(spark.createDataFrame(runs, "workload string, method string, l int, nmi double")).collect()}
    assert best == {"a": True, "b": True, "c": False}


def test_fourier_features_approach_the_kernel(dense):
    ds = dense.filter("id < 60")
    y = numpy_rows(baselines.FourierFeatures(3000, K.Rbf(1.0)).transform(ds, kind="double"))
    x = Dense(numpy_rows(ds, "x"))
    assert np.abs(y @ y.T - K.Rbf(1.0).matrix(x, x)).max() < 0.1
    svd = numpy_rows(baselines.FourierSVD(baselines.FourierFeatures(20, K.Rbf(1.0)), 5).transform(ds, 2, kind="double"))
    assert np.allclose(svd.T @ svd, np.eye(5), atol=1e-6)
    for kernel in (K.Polynomial(), K.Neural(), None):
        with pytest.raises(ValueError):
            baselines.FourierFeatures(5, kernel).transform(ds)


def test_propagation_labels_the_sample_as_its_clusters(rings):
    p = baselines.sample_propagate(rings, K.Rbf(0.8), 2, 200, how="nearest")
    found = {r.id: r.cluster for r in p.transform(rings).collect()}
    assert [found[i] for i in p.landmarks.ids] == p.labels.tolist()
    with pytest.raises(ValueError):
        baselines.sample_propagate(rings, K.Rbf(1.0), 5, 3)


def test_library_baselines(spark, dense, sf_dir):
    assert baselines.mllib_kmeans(dense, 3).count() == 500
    assert baselines.mllib_kmeans(dense, 3, bisecting=True).select("cluster").distinct().count() == 3


def test_spectral_clustering_splits_two_cliques(spark):
    edges = [(a, b, 1.0) for g in (0, 10) for a in range(g, g + 8) for b in range(a + 1, g + 8)] + [(0, 10, 0.1)]
    found = exact.spectral_cluster(spark.createDataFrame(edges, "src long, dst long, weight double"), 2, init=lambda ids: (ids >= 12).astype(int)).to_frame(spark).collect()
    assert len({r.cluster for r in found if r.id < 10}) == 1 and len({r.cluster for r in found}) == 2


def test_indefinite_kernel_drops_negative_eigenvalues(spark, sf_dir):
    ds = features.dense(spark, sf_dir, 16.0)
    lm = collect_landmarks(sample_landmarks(ds, 100))
    block = Nystrom(1000).fit(lm, K.Neural())[0]
    assert block.dropped > 0 and len(block.R) + block.dropped == 100


def test_edges(spark, dense):
    few = dense.filter("id < 6").select("id", "x")
    y = few.withColumnRenamed("x", "y")
    assert cluster(y, 1, max_iter=2).sizes.tolist() == [6]
    assert sorted(cluster(y, 6, init="random", max_iter=2).sizes.tolist()) == [1] * 6
    same = spark.createDataFrame([(i, [1.0, 2.0]) for i in range(5)], "id long, y array<double>")
    kept = cluster(same, 2, init=np.array([[1.0, 2.0], [9.0, 9.0]]), max_iter=2)
    assert kept.sizes.tolist() == [5, 0] and kept.centroids[1].tolist() == [9, 9] and kept.history[0]["empty"] == 1
    assert cluster(same, 2, init=np.array([[1.0, 2.0], [9.0, 9.0]]), max_iter=2, empty="reseed_farthest").centroids[1].tolist() == [1, 2]
    with pytest.raises(ValueError):
        cluster(y, 7, init="random")
    with pytest.raises(ValueError):
        cluster(y, 0)
    lm = collect_landmarks(few)
    for t in (0, 6, 1.0):
        with pytest.raises(ValueError):
            StableProjection(5, t).fit(lm, K.Rbf(1.0))
    with pytest.raises(ValueError):
        StableProjection(5, 2).fit(Landmarks(lm.ids, Dense(np.ones((6, 2)))), K.Rbf(1.0))
    with pytest.raises(MemoryError):
        exact.exact_kkm(dense.select("id", "x"), K.Rbf(1.0), 2, max_n=10)
    with pytest.raises(MemoryError):
        embed(few, Nystrom(6).fit(lm, K.Rbf(1.0)), K.Rbf(1.0), max_block_bytes=10)
    with pytest.raises(ValueError):
        collect_landmarks(few.filter("id = 1"))


def test_invalid_features(spark):
    bad = spark.createDataFrame([(1, [1.0, 2.0]), (2, None), (3, [1.0, float("nan")]), (4, [None, 1.0])], "id long, x array<double>")
    assert dataset.profile(bad) == {"n": 4, "d_min": 2, "d_max": 2, "invalid": 3}
    assert [r.id for r in dataset.validated(bad, "skip").collect()] == [1]
    with pytest.raises(Exception, match="invalid features"):
        dataset.validated(bad).collect()
    with pytest.raises(ValueError):
        from_arrow(spark.createDataFrame([([1.0],), ([1.0, 2.0],)], "x array<double>").toArrow().column("x"))
    with pytest.raises(ValueError):
        dataset.DatasetSpec(feature_col="none").select(bad)
    assert dataset.DatasetSpec(label_col="id").select(bad).columns == ["id", "x", "cls"]


def test_scaling(dense):
    for how, check in (("zscore", lambda x: np.allclose(x.mean(0), 0) and np.allclose(x.std(0), 1)), ("minmax", lambda x: x.min() == 0 and x.max() == pytest.approx(1)), ("unit", lambda x: np.allclose((x * x).sum(1), 1))):
        assert check(numpy_rows(dataset.scale_features(dense, how), "x"))


def test_embedding_plan_has_no_shuffle_and_reads_two_columns(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("id"), C.as_doubles(F.col("embedding")).alias("x"))
    lm = collect_landmarks(sample_landmarks(rows, 30))
    for mode in ("fused", "rounds"):
        y = embed(rows, NystromEnsemble(20, 2).fit(lm, K.Rbf(1.0)), K.Rbf(1.0), mode)
        assert choices.exchanges(y) == 0
    assert choices.read_columns(y)[0] == {"vec_id", "embedding"}
    assert any("lang" in f for f in choices.pushed_filters(spark.read.parquet(f"{sf_dir}/documents.parquet").filter("lang = 'en'").select("doc_id")))


def test_costs_follow_the_formulas():
    s = choices.Scale(n=10**6, row_bytes=8000, l=500, d=1000, m=500, k=100)
    assert choices.iteration_shuffle_bytes(s) < choices.iteration_shuffle_bytes(s, 128 << 20)
    assert choices.store_embedding(s) and not choices.store_embedding(choices.Scale(10**6, 80, 10, 10, 500, 10))
    assert iteration_bytes(10, 4, 50) == 10 * 4 * 55 * 8 and exact_bytes(1000) == 8_000_000
    ledger = CostLedger()
    with ledger.timed("embed", broadcast_bytes=3):
        pass
    assert ledger.embed_s >= 0 and ledger.cluster_s == 0.0 and isinstance(ledger.cluster_s, float)


def test_estimator_round_trip(spark, text, tmp_path):
    model = ScalableKernelKMeans(k=4, method="stable", l=60, m=80, maxIter=3).fit(text)
    a = {r.id: r.cluster for r in model.transform(text).collect()}
    model.save(spark, f"file://{tmp_path}/m")
    assert a == {r.id: r.cluster for r in KernelKMeansModel.load(spark, f"file://{tmp_path}/m").transform(text).collect()}
    assert model.ledger.to_frame(spark).count() == 4
    unstored = ScalableKernelKMeans(k=4, method="stable", l=60, m=80, maxIter=3, storeEmbedding=False).fit(text)
    assert np.allclose(model.centroids, unstored.centroids, atol=1e-4)
    nystrom = ScalableKernelKMeans(k=4, l=100, m=100, tol=0.0).fit(text)
    assert measures.nmi(nystrom.transform(text)).first().nmi > 0.35


def test_cluster_model_round_trip(spark, tmp_path):
    model = ClusterModel(np.array([[1.0, 2.0], [3.0, 4.0]]), np.array([1.0, 2.0]), "l1", [{"iter": 0}])
    model.save(spark, f"file://{tmp_path}/c")
    again = ClusterModel.load(spark, f"file://{tmp_path}/c")
    assert np.allclose(again.centroids, model.centroids) and again.discrepancy == "l1" and again.history == [{"iter": 0}]


def test_sql_functions(spark, dense):
    from landmark_kkm.functions.registry import register

    lm = collect_landmarks(sample_landmarks(dense, 5))
    blocks = Nystrom(5).fit(lm, K.Rbf(1.0))
    y = embed(dense, blocks, K.Rbf(1.0), kind="double").cache()
    model = cluster(y, 3, init="random", max_iter=2)
    assert set(register(spark, blocks, K.Rbf(1.0), model)) >= {"embed", "nearest", "vector_sum", "cluster_partials", "explode_kernel"}
    dense.createOrReplaceTempView("dense_rows")
    y.createOrReplaceTempView("embedded_rows")
    by_sql = {r.id: r.c for r in spark.sql("SELECT id, nearest(embed(x)) AS c FROM dense_rows").collect()}
    assert by_sql == {r.id: r.cluster for r in model.transform(y).collect()}
    total = spark.sql("SELECT vector_sum(y) AS s, vector_mean(y) AS m FROM embedded_rows").first()
    assert np.allclose(total.s, numpy_rows(y).sum(0)) and np.allclose(total.m, numpy_rows(y).mean(0))
    parts = spark.sql("SELECT cluster, sum(g) AS g FROM cluster_partials(TABLE(SELECT y FROM embedded_rows)) GROUP BY cluster").collect()
    assert sum(r.g for r in parts) == 500
    assert spark.sql("SELECT count(*) AS n FROM dense_rows, LATERAL explode_kernel(x)").first().n == 2500


def test_asof_and_interval_joins_match_brute_force(spark):
    rng = np.random.default_rng(0)
    left = [(i, int(rng.integers(4)), int(rng.integers(1000))) for i in range(200)]
    right = [(int(rng.integers(4)), int(rng.integers(1000)), i) for i in range(80)]
    a, b = spark.createDataFrame(left, "id long, k long, at long"), spark.createDataFrame(right, "k long, t long, v long")
    got = {r.id: r.v for r in relational.asof_join(a, b, "at", "t", ["k"]).collect()}
    assert got == {i: max(((t, v) for kk, t, v in right if kk == k and t <= at), default=(0, None))[1] for i, k, at in left}
    stamp = lambda df, c: df.withColumn(c, F.timestamp_seconds(c))
    met = {(r.id, r.v) for r in relational.interval_join(stamp(a, "at"), stamp(b, "t"), "at", "t", 50, ["k"]).collect()}
    assert met == {(i, v) for i, k, at in left for kk, t, v in right if kk == k and 0 <= at - t <= 50}


def test_vector_sum_twins(dense):
    x = numpy_rows(dense, "x")
    row = relational.vector_sum(dense.withColumn("g", F.lit(1)), "g", "x").first()
    assert np.allclose(row["sum"], x.sum(0)) and row.n == 500
    assert relational.salted_count(dense.select("cls", "id"), "cls").agg(F.sum("n")).first()[0] == 500


def test_sources_and_sinks(spark, sf_dir, tmp_path):
    register_views(spark, sf_dir, ("nation", "events"))
    assert spark.sql("SELECT count(*) FROM nation").first()[0] == 25
    assert dict(spark.table("events").dtypes)["ts"] == "timestamp"
    ds = synthetic.planted(spark, "blobs", 100, clusters=4, dimensions=3, partitions=3)
    assert ds.rdd.getNumPartitions() == 3 and ds.filter("cls = '1'").count() == 25
    for kind in ("parquet", "orc", "json"):
        write(ds, f"{tmp_path}/{kind}", kind)
        assert read(spark, f"{tmp_path}/{kind}", kind, schema=ds.schema).count() == 100
    write(ds, "", "noop")
    write(ds, f"{tmp_path}/by", partition_by=("cls",))
    assert read(spark, f"{tmp_path}/by").select("cls").distinct().count() == 4
    (tmp_path / "f.libsvm").write_text("1 1:0.5 3:2.0\n0 2:1.0\n")
    rows = from_libsvm(spark.read.format("libsvm").load(f"{tmp_path}/f.libsvm")).orderBy("id").collect()
    assert rows[0].x.idx == [0, 2] and rows[0].x.val == [0.5, 2.0] and rows[0].x.size == 3
    assert to_ml_vector(ds).first().features.size == 3


def test_streams(spark, sf_dir, tmp_path):
    events = table(spark, sf_dir, "events")
    stream = streams.read_stream(spark, sf_dir, "events")
    batch = {(r.start, r.event_type): r.n for r in streams.windowed_mix(events, "ts", "event_type", "6 hours").collect()}
    assert {(r.start, r.event_type): r.n for r in streams.run_available(streams.windowed_mix(stream, "ts", "event_type", "6 hours"), "complete").collect()} == batch
    appended = streams.run_available(streams.windowed_mix(stream, "ts", "event_type", "6 hours")).count()
    assert 0 < appended < len(batch)  # windows that the watermark has not passed are withheld
    assert streams.run_available(streams.deduplicated(stream, "ts", ["event_id"])).count() == events.count()
    assert streams.run_available(streams.with_table(stream, spark.createDataFrame([("click", 1)], "event_type string, w int"), ["event_type"])).count() == events.count()
    kinds = sorted(r[0] for r in events.select("event_type").distinct().collect())
    model = ClusterModel(np.eye(5), np.ones(5))
    last = streams.run_available(streams.running_histograms(stream, "user_id", "event_type", kinds, model), "update")
    assert {r.user_id: r.events for r in last.collect()} == {r.user_id: r.n for r in events.groupBy("user_id").agg(F.count("*").alias("n")).collect()}


def test_planted_stream_and_mini_batches(spark):
    spark.dataSource.register(synthetic.PlantedClusters)
    source = spark.readStream.format("planted_clusters").options(shape="blobs", clusters="3", dimensions="2", rows="300", rowsPerBatch="100", seed="5", noise="0.3").load()
    batch = synthetic.planted(spark, "blobs", 300, clusters=3, dimensions=2, seed=5, noise=0.3).withColumnRenamed("x", "y")
    start = cluster(batch.limit(100), 3, max_iter=1)
    follower = streams.MiniBatchCentroids(ClusterModel(start.centroids.copy(), start.sizes))
    follower.follow(source.withColumnRenamed("x", "y"))
    moved = costs(numpy_rows(batch), follower.model.centroids, "l2").min(1).mean()
    assert moved < 5 and np.isfinite(follower.model.centroids).all()


def test_features(spark, sf_dir):
    rows = features.multivariate(spark, sf_dir)
    x = np.array([r.x for r in rows.select("x").limit(200).collect()])
    assert x.shape[1] == 54 and rows.select("id").distinct().count() == rows.count()
    assert len(features.multivariate(spark, sf_dir, wide=True, scaled=False).first().x) == 104
    sparse = features.text_sparse(spark, sf_dir).first()
    assert np.linalg.norm(sparse.x.val) == pytest.approx(1, abs=1e-5)
    assert features.strings(spark, sf_dir).count() == table(spark, sf_dir, "conversations").count()
    assert features.labelled_text(spark, sf_dir).count() == 399


def test_gram_counts_by_hand():
    counts = features.gram_counts(["abcabc", "", None, "ab"], 512)
    assert counts.sum(1).tolist() == [4, 1, 1, 1]
    long = features.gram_counts(["abcabc"], 512, n=4)
    assert long.sum() == 3


def test_self_tuned_width_reference_value(spark, sf_dir):
    """The reference was taken on the first 3,000 characters; the feature builder itself takes whole texts."""
    texts = [r.text[:3000] for r in table(spark, sf_dir, "documents").select("text").collect()]
    x = np.sqrt(features.gram_counts(texts, 512))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    assert K.self_tuned_sigma(Dense(x)) == pytest.approx(0.4477, abs=1e-3)


def test_workload_rows(spark, sf_dir):
    found = workloads.run(spark, sf_dir, "w4", l=(30,), methods=("nystrom", "stable"), m=30, max_iter=2)
    assert {r.method for r in found.collect()} == {"nystrom", "stable"} and found.filter("nmi is null").count() == 0


def test_exact_agrees_with_itself_and_runs_share_one_kernel(spark, sf_dir):
    found = workloads.run(spark, sf_dir, "w1", l=(40, 60), methods=("nystrom", "fourier"), m=30, max_iter=3, seeds=2)
    rows = found.collect()
    exact = [r for r in rows if r.method == "exact_kkm"]
    assert len(exact) == 2 and all(r.l == 0 and r.agreement == pytest.approx(1.0) for r in exact)
    assert len(rows) == 2 + 2 * 4 and all(0 <= r.agreement <= 1 and r.label_s > 0 for r in rows if r.method != "exact_kkm")
    assert len({(r.seed, r.nmi) for r in rows if r.method == "fourier"}) == 2  # one run stands for each l
    checks = workloads.checked(found).collect()
    assert all(r.nmi_ok and r.cost_ok and r.exact_ok for r in checks)


def test_packed_vectors_cluster_as_lists_do(spark, dense):
    lm = collect_landmarks(sample_landmarks(dense, 60))
    for family in (Nystrom(40), StableProjection(40)):
        blocks = family.fit(lm, K.Rbf(1.0))
        models = [cluster(embed(dense, blocks, K.Rbf(1.0), kind=kind), 4, family.discrepancy, init="random", max_iter=4) for kind in ("double", "packed")]
        assert np.allclose(models[0].centroids, models[1].centroids, atol=1e-5) and (models[0].sizes == models[1].sizes).all()


def test_class_agreement_by_blocks_is_that_of_all_pairs(spark, text):
    kernel = K.Rbf(0.45)
    names = {r.id: r.cls for r in text.select("id", "cls").collect()}
    rows = collect_landmarks(text.select("id", "x"))
    classes = sorted(set(names.values()))
    labels = np.array([classes.index(names[i]) for i in rows.ids])
    lm = collect_landmarks(sample_landmarks(text.select("id", "x"), 100))
    sums = measures.similarity_sums(text, kernel, block_rows=300)
    assert sums.agg({"n": "sum"}).first()[0] == len(names) ** 2
    nearest = measures.nearest_class(text, sums).cache()
    for family in (Nystrom(100), StableProjection(100)):
        blocks = family.fit(lm, kernel)
        report = measures.discrepancy_report(rows, labels, len(classes), blocks, kernel, family.discrepancy, family.beta(blocks))
        found = measures.class_agreement(text, embed(text, blocks, kernel, kind="packed"), nearest, family.discrepancy)
        assert found == pytest.approx(report["agreement"], abs=0.003)


def test_nearest_classes_and_agreements_of_one_pass_are_those_of_all_pairs(spark, text):
    kernel = K.Rbf(0.45)
    slow = measures.nearest_class(text, measures.similarity_sums(text, kernel)).cache()
    want = {r.id: r.nearest for r in slow.collect()}
    for how in ({}, {"most_rows": 300}, {"least_rows": 100, "centre": np.full(512, 0.04)}):
        found = measures.nearest_class_rbf(text, kernel, **how).collect()
        assert len(found) == len(want) and {r.id: r.nearest for r in found} == want
    lm = [collect_landmarks(sample_landmarks(text.select("id", "x"), l)) for l in (50, 100)]
    ways = [(f.fit(m, kernel), f) for m in lm for f in (Nystrom(100), StableProjection(100))]
    shares = measures.agreements(text, slow, kernel, [(b, f.discrepancy) for b, f in ways])
    for share, (blocks, family) in zip(shares, ways):
        assert share == pytest.approx(measures.class_agreement(text, embed(text, blocks, kernel, kind="packed"), slow, family.discrepancy), abs=0.002)


@pytest.mark.parametrize("at, sigma, apart", [(3000.0, 2e-4, 4e-4), (0.0, 0.5, 1e-5)])
def test_rows_that_rounding_could_move_are_evaluated_anew(spark, at, sigma, apart):
    # far from the centre, float32 takes all rows for the same place; else classes that lie almost on each other leave many rows in doubt
    rng = np.random.default_rng(0)
    x = at + rng.normal(0, sigma, (400, 2))
    rows = [(i, (x[i % 400] + apart * (i // 400)).tolist(), "ab"[i // 400]) for i in range(800)]
    ds = spark.createDataFrame(rows, "id long, x array<double>, cls string").cache()
    kernel = K.Rbf(sigma)
    want = {r.id: r.nearest for r in measures.nearest_class(ds, measures.similarity_sums(ds, kernel)).collect()}
    assert len({*want.values()}) == 2
    assert {r.id: r.nearest for r in measures.nearest_class_rbf(ds, kernel, most_rows=400).collect()} == want


def test_splits_and_forced_deal_over_all_cores(spark):
    from landmark_kkm.session import forced, splits

    few = spark.range(100).repartition(1)
    assert splits(spark.range(0, 10, 1, 3)) == 3 and splits(few.groupBy("id").count()) == int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = forced(few)
    assert dealt.rdd.getNumPartitions() == 8 and splits(dealt) == 8 and dealt.count() == 100
    dealt.unpersist()


def test_queries_match_their_sql(spark, sf_dir):
    """A few of the twins here; the driver compares them all."""
    import duckdb

    from landmark_kkm.queries import ORACLE_SQL, QUERIES

    con = duckdb.connect()
    for name in ("embeddings", "documents", "labels", "events", "customer", "nation", "region"):
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM '{sf_dir}/{name}.parquet'")
    for name in ("q_kernel_rbf", "q_nystrom_l2", "q_lloyd_5iters", "q_nmi_joint", "q_ari", "q_rollup", "q_join_asof"):
        mine, theirs = QUERIES[name](spark, sf_dir), con.sql(ORACLE_SQL[name])
        columns = sorted(mine.columns)
        assert columns == sorted(theirs.columns)
        row = lambda r: tuple(round(v, 5) if isinstance(v, float) else v for v in r)
        assert sorted(map(str, map(row, mine.select(columns).collect()))) == sorted(map(str, map(row, theirs.select(", ".join(columns)).fetchall()))), name


def test_family_checks(dense):
    from landmark_kkm.operators.properties import check_family

    for family in (Nystrom(50), StableProjection(200), NystromEnsemble(40, 2)):
        report = check_family(family, dense, K.Rbf(1.0))
        assert report["linear"] < 1e-9 and report["kernelized"] < 1e-9 and report["blocks"] and 0 <= report["discrepancy"]["agreement"] <= 1


def test_stable_norms_and_pairs(spark, dense):
    from landmark_kkm.operators.properties import reconstruct_pairs, stable_norm, with_local_scale

    few = dense.filter("id < 40")
    x = numpy_rows(few, "x")
    two = np.array([r.norm for r in stable_norm(few, 2, 4000).orderBy("id").collect()])
    one = np.array([r.norm for r in stable_norm(few, 1, 4000).orderBy("id").collect()])
    assert np.allclose(two, np.linalg.norm(x, axis=1), rtol=0.08) and np.allclose(one, np.abs(x).sum(1), rtol=0.15)
    with pytest.raises(ValueError):
        stable_norm(few, 3, 10)
    y = embed(few, Nystrom(40).fit(collect_landmarks(few.select("id", "x")), K.Rbf(1.0)), K.Rbf(1.0), kind="double")
    pairs = spark.createDataFrame([(0, 1), (3, 3)], "i long, j long")
    found = {(r.i, r.j): r.value for r in reconstruct_pairs(y, pairs).collect()}
    assert found[3, 3] == pytest.approx(1) and found[0, 1] == pytest.approx(np.exp(-((x[0] - x[1]) ** 2).sum() / 2))
    local = numpy_rows(with_local_scale(dense, sample=500), "x")
    assert local.shape == (500, 65) and (local[:, -1] > 0).all()


def test_exact_method_takes_more_rows_than_a_kept_kernel(spark):
    n = 20_100
    ds = spark.range(n).select("id", F.array(F.pmod("id", F.lit(3)).cast("double"), (F.col("id") / n).cast("double")).alias("x"))
    found = exact.exact_kkm(ds, K.Rbf(1.0), 3, init=lambda ids: ids % 3, max_iter=2)
    assert len(found.labels) == n and (found.labels == found.ids % 3).all() and found.history[-1]["changed"] == 0


def test_exact_iterations_by_changed_columns_are_those_of_the_whole_matrix(spark, dense):
    rows = dense.select("id", "x")
    lm, kernel = collect_landmarks(rows), K.Rbf(1.0)
    weight = 1.0 + lm.ids % 3
    gram = kernel.matrix(lm.rows, lm.rows)
    labels, history = exact.solve(gram, np.ones(len(lm.ids)), 5, lm.ids % 5, 8, weight=weight)
    weighted = rows.withColumn("w", (1 + F.pmod("id", F.lit(3))).cast("double"))
    for storage in ("persist", "recompute"):
        found = exact.exact_kkm(weighted, kernel, 5, init=lambda ids: ids % 5, max_iter=8, kernel_storage=storage, weight_col="w")
        assert (found.labels == labels).all()
        assert np.allclose([h["cost"] for h in found.history], [h["cost"] for h in history], atol=1e-9)
    one, d = exact.step(gram, np.ones(len(lm.ids)), lm.ids % 5, 5)
    got = {r.id: (r.cluster, r.dist2) for r in exact.exact_step(rows, kernel, 5, lambda ids: ids % 5).collect()}
    assert all(got[i] == (c, pytest.approx(m)) for i, c, m in zip(lm.ids.tolist(), one.tolist(), d.min(1).tolist()))


def _bits(spark, rows: dict[int, list[int]]):
    of = lambda hours: bytes(np.packbits(np.isin(np.arange(16), hours)).tolist())
    return spark.createDataFrame([(i, bytearray(of(h))) for i, h in rows.items()], "id long, x binary")


def test_links_by_shared_bits_lose_no_pair_and_count_equal_rows(spark):
    # 5 and 6 are equal, 7 reaches them through 8 only; 9 and 10 are equal but have one bit; 11 is alone
    found = shared.links(_bits(spark, {5: [0, 1, 2], 6: [0, 1, 2], 7: [4, 5], 8: [1, 2, 4, 5], 9: [9], 10: [9], 11: [12, 13]})).collect()
    assert {tuple(r) for r in found} == {(5, 5, 2, 5), (6, 5, 2, 5), (7, 5, 1, 2), (8, 5, 3, 6), (9, 9, 0, 0), (10, 10, 0, 0), (11, 11, 0, 0)}


def test_links_of_many_copies_make_no_row_for_a_pair(spark):
    found = shared.links(_bits(spark, {i: [i % 4, 4 + i % 4, 8] for i in range(30_000)}))
    assert found.agg(F.count_distinct("component"), F.min("links"), F.max("links"), F.min("weight")).first()[:] == (4, 7499, 7499, 3 * 7499)


def test_graphs_from_bits_are_those_of_the_edges(spark, sf_dir):
    edges, hours = features.event_graph(spark, sf_dir), features.user_hours(spark, sf_dir)
    both = edges.unionByName(edges.selectExpr("dst AS src", "src AS dst", "weight")).groupBy("src").agg(F.count("*"), F.sum("weight")).collect()
    assert {tuple(r) for r in shared.links(hours).select("id", "links", "weight").collect()} == {tuple(r) for r in both}
    by_edges, by_bits = exact.spectral_cluster(edges, 4, init="partition"), shared.spectral_cluster(hours, 4, init="partition")
    assert (by_edges.ids == by_bits.ids).all() and (by_edges.labels == by_bits.labels).all()
    assert shared.power_iteration(hours, 4).agg(F.count("*"), F.count_distinct("cluster")).first()[:] == (150, 4)


def test_the_spectral_query_moves_rows_from_its_start(spark, tmp_path):
    # two groups of users, the bulk of whose hours lie in different halves of a week: with a shift of 1 every user stays where the start put them
    rng, rows = np.random.default_rng(1), []
    for user in range(80):
        hours = np.append(rng.choice(84, 30, False) + 84 * (user % 2), rng.choice(168, 4, False))
        rows += [(user, f"2024-01-{1 + h // 24:02d} {h % 24:02d}:05:00") for h in hours.tolist()]
    spark.createDataFrame(rows, "user_id long, ts string").selectExpr("user_id", "to_timestamp(ts) AS ts").write.parquet(f"{tmp_path}/events.parquet")
    users = features.user_hours(spark, str(tmp_path))
    stuck = shared.spectral_cluster(users, 2, init="partition")
    assert [h["changed"] for h in stuck.history] == [0]
    found = shared.spectral_cluster(users, 2, shift=0.0, init="partition", max_iter=1000, patience=10)
    assert len({*zip((found.ids % 2).tolist(), found.labels.tolist())}) == 2
    clusters = {r.id: r.cluster for r in QUERIES["q_spectral"](spark, str(tmp_path)).collect()}
    start = dict(zip(stuck.ids.tolist(), (np.arange(80) % 4).tolist()))
    groups = [{clusters[u] for u in range(g, 80, 2)} for g in (0, 1)]
    assert clusters != start and not groups[0] & groups[1]


def test_neighbours_of_landmarks_are_those_of_the_graph(spark, sf_dir):
    of = [3, 10, 77]
    found = features.neighbours(spark, sf_dir, spark.createDataFrame([(i,) for i in of], "id long"))
    want = {}
    for a, b, w in features.event_graph(spark, sf_dir).collect():
        for i, j in ((a, b), (b, a)):
            if j in of:
                want.setdefault(i, {})[j] = float(w)
    assert {r.id: {k: v for k, v in r.x.items() if k != -1} for r in found.collect() if len(r.x) > 1} == want


def test_class_sums_copy_no_row_for_a_block(spark, text):
    found = measures.similarity_sums(text, K.Rbf(0.45), block_rows=100)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "FlatMapCoGroups" not in plan and "Generate explode(sequence" not in plan
    assert found.count() == text.count() * text.select("cls").distinct().count()


def test_exact_method_takes_any_number_of_rows(spark, dense, monkeypatch):
    many = spark.range(500_001).select("id", F.array(F.col("id") / 8).alias("x"))
    ids, rows, _ = exact._collected(many, exact.MAX_ROWS, 42, None)
    assert len(ids) == 500_001 and rows.rows.dtype == np.float32 and (rows.take(np.arange(9)).rows[:, 0] == ids[:9] / 8).all()
    whole = exact.exact_kkm(dense.select("id", "x"), K.Neural(), 4, max_iter=3, kernel_storage="recompute")
    monkeypatch.setattr(exact, "PIECE", 100)
    parts = exact.exact_kkm(dense.select("id", "x"), K.Neural(), 4, max_iter=3, kernel_storage="recompute")
    assert (whole.ids == parts.ids).all() and (whole.labels == parts.labels).all()
    assert np.allclose([h["cost"] for h in whole.history], [h["cost"] for h in parts.history])


def test_sparse_products_take_memory_by_their_entries():
    import tracemalloc

    rng = np.random.default_rng(3)
    rows = lambda n, each: Sparse(1 << 16, np.arange(n + 1) * each, np.concatenate([np.append(0, 1 + rng.choice((1 << 16) - 1, each - 1, replace=False)) for _ in range(n)]), rng.random(n * each))
    left, right = rows(300, 150), rows(1000, 150)
    tracemalloc.start()
    found = left.dot(right)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    laid = np.zeros((300, 1 << 16))
    laid[np.repeat(np.arange(300), 150), left.idx] = left.val
    wanted = [(laid[:, right.idx[a:b]] * right.val[a:b]).sum(1) for a, b in zip(right.start[:-1], right.start[1:])]
    assert np.allclose(found, np.stack(wanted, 1)) and peak < 128 << 20
    twice = Sparse(5, np.array([0, 0, 3, 3]), np.array([4, 1, 4]), np.array([1.0, 2.0, 3.0]))  # rows without entries, and a feature twice in a row
    assert twice.dot(twice).tolist() == [[0, 0, 0], [0, 20, 0], [0, 0, 0]] and twice.dot(twice.take([0])).tolist() == [[0], [0], [0]]


def test_workload_gives_its_broadcasts_back(spark, sf_dir, monkeypatch):
    from pyspark import Broadcast

    from landmark_kkm import session

    before, destroyed, destroy = session.held(), [], Broadcast.destroy
    monkeypatch.setattr(Broadcast, "destroy", lambda self, blocking=False: (destroyed.append(self.value), destroy(self, blocking)))
    workloads.run(spark, sf_dir, "w5", (20, 30), max_iter=1).collect()
    models = [v for v in destroyed if isinstance(v, tuple) and (isinstance(v[0], list) or hasattr(v[0], "start"))]
    assert session.held() == before and len(models) == 6  # landmarks and coefficients of each run


def test_sparse_text_does_not_shuffle_words(spark, sf_dir):
    found = features.text_sparse(spark, sf_dir)
    texts = dict(table(spark, sf_dir, "documents").select("doc_id", "text").collect())
    assert choices.exchanges(found.select("id", "x")) <= 1  # that which deals a small file over the cores
    row = found.filter("size(x.idx) > 20").first()
    assert list(row.x.idx) == sorted(set(row.x.idx)) and len(row.x.idx) <= len(texts[row.id].split()) * 3


def test_loop_sends_vectors_only(spark, monkeypatch):
    from landmark_kkm.operators import cluster as loop

    rows = spark.range(60).select("id", F.array(F.col("id") % 7 / 1.0, F.col("id") % 5 / 1.0).alias("y"), (F.col("id") % 2 + 1.0).alias("w"), F.lit("c").alias("cls"))
    seen, merged = [], loop.merged
    monkeypatch.setattr(loop, "merged", lambda partials, n: (seen.append(partials._jdf.queryExecution().analyzed().toString()), merged(partials, n))[1])
    plain, weighted = (cluster(rows, 3, init="random", max_iter=3, weight_col=w) for w in (None, "w"))
    assert plain.sizes.sum() == 60 and weighted.sizes.sum() == 90
    assert all("Project [y#" in plan for plan in seen) and len(seen) == 6
    y = np.random.default_rng(5).random((1000, 3)).astype(np.float32)  # more rows of a key than are added up at a time
    held = vectors.Partials(far=True)
    keys, w = np.arange(1000) % 2, np.arange(1000) / 7
    held.add(keys, y, w, y[:, 0], np.ones(1000, bool))
    for k, row in held.held.items():
        at = keys == k
        assert np.allclose(row[0], w[at] @ y[at].astype(float)) and (row[5] == y[at][y[at][:, 0].argmax()]).all()


def test_embedding_takes_memory_by_its_result(monkeypatch):
    import sys
    import tracemalloc

    import pyarrow as pa

    module = sys.modules["landmark_kkm.operators.embed"]
    rng = np.random.default_rng(4)
    lists = lambda v, n: pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * 200), pa.array(v))
    x = pa.StructArray.from_arrays([pa.array(np.full(8000, 1 << 16, np.int32)), lists(rng.integers(0, 1 << 16, 8000 * 200).astype(np.int32), 8000), lists(rng.random(8000 * 200).astype(np.float32), 8000)], ["size", "idx", "val"])
    lm = Landmarks(np.arange(50), from_arrow(x.slice(0, 50)))
    blocks = Nystrom(40).fit(lm, K.Rbf(5.0))
    wanted = blocks[0].apply(from_arrow(x.slice(7000, 300)), K.Rbf(5.0))
    monkeypatch.setattr(module, "CELLS", 50 * 400)
    tracemalloc.start()
    y = module.embedded(x, blocks, K.Rbf(5.0), np.float32)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert np.allclose(y[7000:7300], wanted, atol=1e-5) and peak < 24 << 20  # 8,000 rows taken apart at once are 25.6 MB


def test_few_partial_sums_come_without_a_shuffle(spark, dense, monkeypatch):
    from landmark_kkm.operators import cluster as loop

    rows, seen, merged = dense.select("id", F.col("x").alias("y")), [], loop.merged
    monkeypatch.setattr(loop, "merged", lambda partials, n: (seen.append(n), merged(partials, n))[1])
    found = []
    for most in (vectors.GATHERED, 0):
        monkeypatch.setattr(vectors, "GATHERED", most)
        found.append([cluster(rows, 5, empty=empty, max_iter=3, tol=0.0) for empty in ("keep", "reseed_farthest")])
    assert all(n == 0 for n in seen[: len(seen) // 2]) and all(n > 0 for n in seen[len(seen) // 2 :])
    for a, b in zip(*found):
        assert np.allclose(a.centroids, b.centroids) and (a.sizes == b.sizes).all() and [h["changed"] for h in a.history] == [h["changed"] for h in b.history]
    assert vectors.levels(300, 1 << 20) == 300 and vectors.merged(rows.limit(0).mapInArrow(lambda it: vectors.summed_by_key(it, None), vectors.PARTIAL_DDL), 0) == []


def test_sparse_products_by_table_and_by_search_are_equal(monkeypatch):
    from landmark_kkm.functions import payloads

    rng = np.random.default_rng(6)
    rows = lambda n, of: Sparse(of, np.arange(n + 1) * 9, np.concatenate([rng.choice(of, 9, replace=False) for _ in range(n)]), rng.random(n * 9))
    left, right = rows(70, 200), rows(40, 90)
    by_table, searched = left.dot(right), []
    search = np.searchsorted
    monkeypatch.setattr(np, "searchsorted", lambda *a: (searched.append(1), search(*a))[1])
    assert (left.dot(right) == by_table).all() and not searched
    monkeypatch.setattr(payloads, "TABLE", 0)
    assert (left.dot(right) == by_table).all() and searched and by_table.any()


def test_forced_leaves_no_core_waiting_for_the_last_partitions(spark):
    from landmark_kkm.session import ROUNDS, forced

    for n, wanted in ((11, 8), (8, 8), (23, 16), (8 * ROUNDS + 1, 8 * ROUNDS + 1)):
        found = forced(spark.range(0, 500, 1, n))
        assert found.rdd.getNumPartitions() == wanted and found.agg(F.sum("id"), F.count("*")).first()[:] == (500 * 499 // 2, 500)
        found.unpersist()


def test_kept_text_is_split_once_and_given_back(spark, sf_dir):
    from landmark_kkm import session

    since, before = session.held(), spark.sparkContext._jsc.getPersistentRDDs().size()
    found = features.text_sparse(spark, sf_dir, kept=True)
    assert "InMemoryRelation" in found._jdf.queryExecution().executedPlan().toString() and session.held() == since + 1
    same = lambda df: {r.id: (r.cls, r.source, list(r.x.idx), list(r.x.val)) for r in df.collect()}
    assert same(found) == same(features.text_sparse(spark, sf_dir))
    session.release(since)
    assert session.held() == since and spark.sparkContext._jsc.getPersistentRDDs().size() == before


def test_starts_sort_few_rows_and_are_those_of_the_whole_sort(spark, monkeypatch):
    from landmark_kkm.operators import cluster as loop
    from landmark_kkm.operators.landmarks import digest

    rows = spark.range(0, 4000, 1, 8).select("id", F.array(F.col("id") / 8, F.col("id") % 5 / 1.0).alias("y")).cache()
    whole = rows.withColumn("_digest", digest(seed=3)).orderBy("_digest", "id").limit(7).collect()
    sorted_rows, order = [], type(rows).orderBy
    monkeypatch.setattr(type(rows), "orderBy", lambda self, *c: (sorted_rows.append(self.count()), order(self, *c))[1])
    assert (loop.first_centroids(rows, 7, "random", "l2", 3) == np.array([r.y for r in whole])).all()
    monkeypatch.setattr(loop, "SEEDING_ROWS", 50)
    assert loop.first_centroids(rows, 7, "kmeans++", "l2", 3).shape == (7, 2) and max(sorted_rows) < 200
    with pytest.raises(ValueError, match="need"):
        loop.first_centroids(rows.limit(5), 7, "random", "l2", 3)
    rows.unpersist()


def test_methods_of_a_run_share_their_landmarks(spark, sf_dir, monkeypatch):
    sizes, draw = [], workloads.sample_landmarks
    monkeypatch.setattr(workloads, "sample_landmarks", lambda ds, l, **how: (sizes.append(l), draw(ds, l, **how))[1])
    runs = workloads.run(spark, sf_dir, "w5", (20, 30), max_iter=1).collect()
    assert sorted(sizes) == [20, 30, workloads.TUNING_ROWS] and len(runs) == 6
