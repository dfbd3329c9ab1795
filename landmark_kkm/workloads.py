"""The experiment workloads on the given tables: every method at each number of landmarks, over seeds, with agreement and times."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from landmark_kkm.functions.kernels import Kernel, Neural, Polynomial, Rbf, self_tuned_sigma
from landmark_kkm.operators import baselines, measures, shared
from landmark_kkm.operators.cluster import cluster
from landmark_kkm.operators.coefficients import Nystrom, NystromEnsemble, StableProjection
from landmark_kkm.operators.embed import embed
from landmark_kkm.operators.exact import exact_kkm
from landmark_kkm.operators.landmarks import Landmarks, collect_landmarks, sample_landmarks
from landmark_kkm.operators.ledger import CostLedger, centroid_bytes, embed_bytes, iteration_bytes
from landmark_kkm.session import forced, held, release, splits
from landmark_kkm.sources import features

MEDIUM = ("fourier", "fourier_svd", "span_kkm", "nystrom", "stable")
LARGE = ("sample_propagate", "nystrom", "stable")
RUN_DDL = (
    "workload string, method string, l int, m int, k int, seed int, nmi double, agreement double, embed_s double, cluster_s double, label_s double, "
    "iterations int, cost_falls boolean, broadcast_bytes long, shuffle_bytes long"
)
#: Methods that no number of landmarks changes: they run once, and their row stands for each l, as in the published tables.
WITHOUT_LANDMARKS = ("fourier", "fourier_svd")
#: Rows that the width of a workload's kernel is tuned on.
TUNING_ROWS = 1000


@dataclass
class Workload:
    """What to cluster, with which kernel (None: RBF of self-tuned width), into how many clusters, by which methods."""

    name: str
    data: Callable[[SparkSession, str], DataFrame]
    k: int
    methods: tuple[str, ...]
    kernel: Kernel | None = None
    l: tuple[int, ...] = (50, 100, 300)
    m: int = 1000
    t: float = 0.4
    D: int = 500
    max_iter: int = 20
    tol: float | None = None
    exact: bool = False
    label: str = "cls"
    how: dict = field(default_factory=dict)


def kept_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return features.text_sparse(spark, sf_dir, kept=True)


#: The medium ones run until no label changes, 20 iterations at most; the large ones always 20.
WORKLOADS = {
    "w1": Workload("w1", features.dense, 10, MEDIUM, exact=True, tol=0.0),
    "w2": Workload("w2", features.text_grams, 4, MEDIUM, tol=0.0),
    "w3": Workload("w3", lambda s, d: features.dense(s, d, 16.0), 10, MEDIUM[2:], kernel=Neural(0.0045, 0.11), exact=True, tol=0.0),
    "w4": Workload("w4", features.text_grams, 4, MEDIUM[2:], kernel=Polynomial(5, 1.0), tol=0.0),
    "w5": Workload("w5", kept_text, 4, LARGE, l=(500, 1000, 1500), m=500),
    "w5b": Workload("w5b", kept_text, 103, LARGE, l=(500, 1000, 1500), m=500, label="source"),
    "w6": Workload("w6", features.multivariate, 7, LARGE, l=(500, 1000, 1500), m=500),
    "w7": Workload("w7", lambda s, d: features.multivariate(s, d, wide=True), 164, LARGE, l=(500, 1000, 1500), m=500),
}


def kernel_of(ds: DataFrame, w: Workload) -> Kernel:
    """One kernel for all runs of a workload: its own, or an RBF whose width is tuned on TUNING_ROWS rows, so that runs differ in nothing but method, l and seed."""
    return w.kernel or Rbf(self_tuned_sigma(collect_landmarks(sample_landmarks(ds.select("id", "x"), TUNING_ROWS)).rows))


def drawn(ds: DataFrame, l: int, seed: int) -> Landmarks:
    return collect_landmarks(sample_landmarks(ds.select("id", "x"), l, seed=seed), seed)


def one_run(ds: DataFrame, w: Workload, method: str, l: int, seed: int, kernel: Kernel, m: int | None = None, reference: DataFrame | None = None, landmarks: Landmarks | None = None, **how) -> tuple[tuple, DataFrame]:
    """A row of RUN_DDL: the method on ds with its class labels, and its agreement (NMI) with a reference clustering (id, cluster); and its own clustering, persisted.

    Embedding, iterations and the last labelling pass are timed apart."""
    m, ledger, bytes_sent, bytes_shuffled = m or w.m, CostLedger(), 0, 0
    loop = {"max_iter": w.max_iter, "tol": w.tol, "seed": seed} | how
    rows, y, model = ds.select("id", "x", "cls"), None, None
    if method == "exact_kkm":
        with ledger.timed("cluster"):
            result = forced(exact_kkm(ds.select("id", "x"), kernel, w.k, seed=seed, max_iter=loop["max_iter"]).to_frame(ds.sparkSession).join(ds.select("id", "cls"), "id"))
    else:
        landmarks = landmarks or drawn(ds, l, seed)
    if method == "sample_propagate":
        with ledger.timed("cluster"):
            labeller = baselines.sample_propagate(rows, kernel, w.k, l, seed=seed, landmarks=landmarks)
        with ledger.timed("label"):
            result = forced(labeller.transform(rows))
    elif method != "exact_kkm":
        discrepancy = "l2"
        with ledger.timed("embed"):
            if method == "span_kkm":
                pass
            elif method == "fourier":
                y = forced(baselines.FourierFeatures(w.D, kernel, seed).transform(rows))
            elif method == "fourier_svd":
                y = forced(baselines.FourierSVD(baselines.FourierFeatures(w.D, kernel, seed)).transform(rows, w.k))
            else:
                family = {"nystrom": Nystrom(m), "stable": StableProjection(m, w.t, seed=seed), "stable_eigen": StableProjection(m, w.t, root="eigen", seed=seed), "nystrom_ensemble": NystromEnsemble(m, 4)}[method]
                discrepancy = family.discrepancy
                blocks = family.fit(landmarks, kernel)
                bytes_sent = embed_bytes(blocks)
                y = forced(embed(rows, blocks, kernel, kind="packed"))
        with ledger.timed("cluster"):
            if method == "span_kkm":
                y, model = baselines.span_kkm(rows, kernel, w.k, l, landmarks=landmarks, **loop)
            else:
                model = cluster(y, w.k, discrepancy, **loop)
        with ledger.timed("label"):
            result = forced(model.transform(y))
        size = model.centroids.shape[1]
        bytes_sent += centroid_bytes(w.k, size) * len(model.history)
        bytes_shuffled = iteration_bytes(splits(ds), w.k, size) * len(model.history)
        y.unpersist()
    nmi = measures.nmi(result).first()
    agreement = measures.nmi(result.join(reference.select("id", F.col("cluster").alias("other")), "id"), "cluster", "other").first()["nmi"] if reference is not None else None
    cost = [h["cost"] for h in model.history] if model else []
    falls = all(b <= a + 1e-5 * abs(a) + 1e-9 for a, b in zip(cost, cost[1:])) if cost and model.discrepancy == "l2" else None
    figures = ledger.embed_s, ledger.cluster_s, ledger.seconds("label"), len(cost) or None, falls, int(bytes_sent), int(bytes_shuffled)
    return (w.name, method, l, m, w.k, seed, float(nmi["nmi"]) if nmi else None, agreement, *figures), result


def run(spark: SparkSession, sf_dir: str, name: str, l: tuple[int, ...] | None = None, seeds: int = 1, methods: tuple[str, ...] | None = None, with_exact: bool | None = None, **how) -> DataFrame:
    """A row for each method, number of landmarks and seed; with_exact adds the exact method (l is 0) and every run's agreement with it at the same seed."""
    w, since = WORKLOADS[name], held()
    ds = forced(w.data(spark, sf_dir).select("id", "x", F.col(w.label).alias("cls")))
    release(since)
    kernel, out = kernel_of(ds, w), []
    for seed in range(seeds):
        reference, samples = None, {}  # all methods take the same landmarks
        if w.exact if with_exact is None else with_exact:
            row, reference = one_run(ds, w, "exact_kkm", 0, seed, kernel, **{k: v for k, v in how.items() if k == "max_iter"})
            row = (*row[:7], float(measures.nmi(reference.withColumn("other", F.col("cluster")), "cluster", "other").first()["nmi"]), *row[8:])
            out.append(row)
        for method in methods or w.methods:
            row = None
            for size in l or w.l:
                if row is None or method not in WITHOUT_LANDMARKS:
                    since = held()
                    if size not in samples:
                        samples[size] = drawn(ds, size, seed)
                    row, found = one_run(ds, w, method, size, seed, kernel, reference=reference, landmarks=samples[size], **how)
                    found.unpersist()
                    release(since)
                out.append((*row[:2], size, *row[3:]))
        if reference is not None:
            reference.unpersist()
    ds.unpersist()
    return spark.createDataFrame(out, RUN_DDL)


def scaling_l(spark: SparkSession, sf_dir: str, l: tuple[int, ...] = (500, 1000, 1500)) -> DataFrame:
    """Embedding and clustering seconds by the number of landmarks, m fixed."""
    return run(spark, sf_dir, "w6", l, methods=("nystrom", "stable"))


def scaling_k(spark: SparkSession, sf_dir: str, l: int = 500) -> DataFrame:
    """Clustering seconds by the number of clusters and the discrepancy (nystrom: l2, stable: l1), with l1_share, the seconds of l1 over those of l2."""
    return with_l1_share(run(spark, sf_dir, "w6", (l,), methods=("nystrom", "stable")).unionByName(run(spark, sf_dir, "w7", (l,), methods=("nystrom", "stable"))))


def with_l1_share(both: DataFrame) -> DataFrame:
    """runs with l1_share: by workload, the clustering seconds of stable (l1) over those of nystrom (l2)."""
    ratio = both.groupBy("workload").agg((F.sum(F.when(F.col("method") == "stable", F.col("cluster_s"))) / F.sum(F.when(F.col("method") == "nystrom", F.col("cluster_s")))).alias("l1_share"))
    return both.join(F.broadcast(ratio), "workload")


def total(spark: SparkSession, sf_dir: str, l: int = 500) -> DataFrame:
    """(method, seconds): the whole of both methods on the users of the events table, and power iteration clustering on the graph of the same users."""
    import time

    out = []
    w = Workload("total", features.users, 4, ("nystrom", "stable"), l=(l,), m=500)
    for method in w.methods:
        began = time.perf_counter()
        ds = forced(w.data(spark, sf_dir).select("id", "x", "cls"))
        one_run(ds, w, method, l, 0, kernel_of(ds, w))[1].unpersist()
        ds.unpersist()
        out.append((method, time.perf_counter() - began))
    began = time.perf_counter()
    shared.power_iteration(features.user_hours(spark, sf_dir), w.k).count()
    return spark.createDataFrame([*out, ("power_iteration", time.perf_counter() - began)], "method string, seconds double")


def ablations(spark: SparkSession, sf_dir: str, l: int = 100) -> DataFrame:
    """(what, setting, nmi, seconds) on the text workload: combiner, embedding modes, root, t, m and first centroids."""
    import time

    w = WORKLOADS["w2"]
    ds = forced(w.data(spark, sf_dir))
    landmarks = collect_landmarks(sample_landmarks(ds.select("id", "x"), l))
    kernel = Rbf(self_tuned_sigma(landmarks.rows))
    out = []

    def tried(what: str, setting: str, family, mode: str = "fused", **how) -> None:
        began = time.perf_counter()
        y = forced(embed(ds, family.fit(landmarks, kernel), kernel, mode))
        model = cluster(y, w.k, family.discrepancy, max_iter=how.pop("max_iter", 4), **how)
        nmi = measures.nmi(model.transform(y)).first()["nmi"]
        y.unpersist()
        out.append((what, setting, float(nmi), time.perf_counter() - began))

    for mode in ("fused", "rounds", "staged"):
        tried("mode", mode, NystromEnsemble(80, 4), mode)
    for combine in (True, False):
        tried("combiner", str(combine), Nystrom(50), combine=combine, max_iter=2)
    for root in ("symmetric", "eigen"):
        tried("root", root, StableProjection(200, 0.4, root=root))
    for t in (0.05, 0.2, 0.4, 0.8):
        tried("t", str(t), StableProjection(200, t))
    for m in (50, 100, 200, 500, 1000):
        tried("m", str(m), StableProjection(m, 0.4))
    for init in ("random", "kmeans++", "partition"):
        tried("init", init, Nystrom(100), init=init)
    ds.unpersist()
    return spark.createDataFrame(out, "what string, setting string, nmi double, seconds double")


def checked(runs: DataFrame) -> DataFrame:
    """What must hold of any run: a normalised measure lies in [0, 1], the l2 cost of nystrom never rises, and the exact method agrees with itself."""
    within = lambda c: F.coalesce(F.col(c).between(-1e-9, 1 + 1e-9), F.lit(True))
    cost = F.when(F.col("method") == "nystrom", F.coalesce("cost_falls", F.lit(False))).otherwise(F.coalesce("cost_falls", F.lit(True)))
    itself = F.when(F.col("method") == "exact_kkm", F.abs(F.col("agreement") - 1) < 1e-9).otherwise(F.lit(True))
    return runs.select("workload", "method", "l", "m", "k", "seed", (F.col("nmi").isNotNull() & within("nmi") & within("agreement")).alias("nmi_ok"), cost.alias("cost_ok"), itself.alias("exact_ok"))


def expected(name: str) -> str:
    """SQL for checked(run(name)) with one seed: a row for each method and number of landmarks, all as they must be."""
    w = WORKLOADS[name]
    rows = [("exact_kkm", 0)] * w.exact + [(method, l) for method in w.methods for l in w.l]
    return "SELECT '%s' AS workload, method, l::INT AS l, %d::INT AS m, %d::INT AS k, 0::INT AS seed, true AS nmi_ok, true AS cost_ok, true AS exact_ok FROM (VALUES %s) t(method, l)" % (name, w.m, w.k, ", ".join(f"('{a}', {b})" for a, b in rows))


def ttest_table(runs: DataFrame) -> DataFrame:
    """Means, deviations and which methods are not significantly below the best, for each workload and number of landmarks."""
    return measures.best_by_ttest(runs.filter(F.col("nmi").isNotNull()))


def agreement_with_exact(ds: DataFrame, kernel: Kernel, k: int, l: int, family, labels: np.ndarray, seed: int = 42) -> dict:
    """Discrepancy quality of a family on a small dataset, for labels in digest order of the ids."""
    rows = collect_landmarks(ds.select("id", "x"), seed)
    landmarks = collect_landmarks(sample_landmarks(ds.select("id", "x"), l, seed=seed), seed)
    blocks = family.fit(landmarks, kernel)
    return measures.discrepancy_report(rows, labels, k, blocks, kernel, family.discrepancy, family.beta(blocks))
