"""The experiments: time against recall, index budgets and indexing times, and the effect of k, m and the number of probes.

Each returns a DataFrame of measured rows (ROW), one for each parameter draw and run; `measures.summarize`, `pareto`
and `budget_curve` reduce them. Grids are arguments; the defaults suit a laptop, `theory.grid` has the published ones.
"""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ringann.functions import measures, theory
from ringann.operators import baselines, families, search
from ringann.operators.probe import probe_grid
from ringann.sources.staging import shared_dir

ROW = "method string, params string, draw int, run int, recall double, ratio double, seconds double, build_seconds double, index_bytes long"


class Bench:
    """Measures searches of queries(qid, vec) in data(obj_id, vec), vectors of length d; times are of a whole batch, divided by its queries."""

    def __init__(self, spark: SparkSession, data: DataFrame, queries: DataFrame, d: int, metric: str = "euclidean", k: int = 10, width: float = 2.0, runs: int = 1):
        self.spark, self.data, self.queries, self.d, self.metric, self.k, self.width, self.runs = spark, data.persist(), queries.persist(), d, metric, k, width, runs
        self.n, self.asked = self.data.count(), self.queries.count()
        self.rows: list[tuple] = []
        self.truths: dict[int, DataFrame] = {}

    def family(self, m: int, draw: int):
        return families.RandomProjection(self.d, m, self.width, draw) if self.metric == "euclidean" else families.CrossPolytope(self.d, m, draw, "hadamard")

    def truth(self, k: int) -> DataFrame:
        if k not in self.truths:
            self.truths[k] = search.exact_knn(self.data, self.queries, k, self.metric).persist()
        return self.truths[k]

    def add(self, method: str, params: dict, draw: int, result: DataFrame, build: float = 0.0, size: int = 0, k: int | None = None) -> None:
        k = k or self.k
        acc = measures.recall(result, self.truth(k), k).agg(F.avg("recall")).first()[0]
        ratio = measures.overall_ratio(result, self.truth(k)).agg(F.avg("ratio")).first()[0]
        for run in range(self.runs):
            self.rows.append((method, json.dumps(params, sort_keys=True), draw, run, acc, ratio, measures.timed(result) / max(1, self.asked), build, size))

    def index(self, m: int, draw: int) -> tuple[DataFrame, object, float, int]:
        """(written index, family, seconds of building it, its bytes)."""
        fam = self.family(m, draw)
        path = f"{shared_dir(self.spark).rstrip('/')}/ring-{self.metric}-{self.d}-{m}-{draw}"
        build = measures.timed_call(lambda: search.write_index(search.build_index(self.data, fam, rows=self.n), path))
        index = search.read_index(self.spark, path)
        return index, fam, build, search.index_stats(index).first()["index_bytes"]

    def ring(self, ms, lams, probes=(1,), draws=(1,), ks=(None,)) -> None:
        """probes are numbers, or "grid" for the published multiples of m."""
        for draw in draws:
            for m in ms:
                index, fam, build, size = self.index(m, draw)
                for lam in lams:
                    for p in probe_grid(m) if probes == "grid" else probes:
                        for k in ks:
                            found = search.ring_search(index, fam, self.queries, lam, k or self.k, n_probes=p)
                            self.add("ring" if p == 1 else "ring_probe", {"m": m, "lam": lam, "probes": p, "k": k or self.k}, draw, found, build, size, k)

    def rivals(self, concat, thresholds, ms, probes: int = 4, draws=(1,)) -> None:
        """Sizes of rivals' indexes: their entries packed, an id of 8 bytes with codes of 4 or projections of 8."""
        a, q, k, n = self.data, self.queries, self.k, self.n
        for draw in draws:
            for kk, tables in concat:
                fam, size = self.family(kk * tables, draw), n * tables * (8 + 4 * kk)
                build = measures.timed_call(lambda: baselines._buckets(families.encode(a, fam, False), kk, tables).write.format("noop").mode("overwrite").save())  # noqa: B023
                self.add("static_concat", {"K": kk, "L": tables}, draw, baselines.static_concat(a, fam, q, kk, tables, k), build, size)
                self.add("multiprobe_static", {"K": kk, "L": tables, "probes": probes}, draw, baselines.multiprobe_static(a, fam, q, kk, tables, k, probes), build, size)
            for m in ms:
                fam = self.family(m, draw)
                build = measures.timed(families.encode(a, fam, False))
                for t in thresholds:
                    self.add("collision_count", {"m": m, "l": t}, draw, baselines.collision_count(a, fam, q, t, k), build, n * m * 12)
            if self.metric == "euclidean":
                self.add("projected_incremental", {"d": 6, "budget": 100}, draw, baselines.projected_incremental(a, q, self.d, 6, 100, k, seed=draw), 0.0, n * 8 * 7)
                self.add("query_aware_count", {"m": 16, "l": 10}, draw, baselines.query_aware_count(a, q, self.d, 16, self.width / 2, 10, k, 2.0, 4, draw), 0.0, n * 16 * 16)
                self.add("query_aware_blocked", {"m": 16, "l": 8, "leaf": max(100, n // 8)}, draw, baselines.query_aware_blocked(a, q, self.d, 16, 2 * self.width, 8, k, max(100, n // 8), 10, 10, 3, draw), 0.0, n * 16 * 16)

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, ROW)


def time_recall(spark, data, queries, d: int, metric: str = "euclidean", k: int = 10, ms=(16, 64), lams=(20, 100), concat=((2, 8), (3, 16)), thresholds=(2, 4), width: float = 2.0, draws=(1,), runs: int = 1) -> DataFrame:
    """Every method over its grid, at one k: recall, ratio, query and indexing time and index size."""
    b = Bench(spark, data, queries, d, metric, k, width, runs)
    for m in ms:
        b.ring([m], lams, (1, m + 1), draws)
    b.rivals(concat, thresholds, ms, draws=draws)
    return b.frame()


def sensitivity_to_k(spark, data, queries, d, metric="euclidean", ks=(1, 2, 5, 10, 20, 50, 100), m=64, lam=100, width=2.0, draws=(1,)) -> DataFrame:
    b = Bench(spark, data, queries, d, metric, width=width)
    b.ring([m], [lam], (1,), draws, ks)
    return b.frame()


def impact_of_m(spark, data, queries, d, metric="euclidean", ms=(8, 16, 32, 64, 128, 256, 512), lam=100, k=10, width=2.0, draws=(1,)) -> DataFrame:
    b = Bench(spark, data, queries, d, metric, k, width)
    b.ring(ms, [lam], (1,), draws)
    return b.frame()


def impact_of_probes(spark, data, queries, d, metric="euclidean", m=128, lams=(20, 100), k=10, width=2.0, draws=(1,)) -> DataFrame:
    b = Bench(spark, data, queries, d, metric, k, width)
    b.ring([m], lams, "grid", draws)
    return b.frame()


def tune_width(data: DataFrame, tuning: DataFrame, d: int, widths, m: int = 32, lam: int = 100, k: int = 10) -> float:
    """The width of the best mean recall on tuning(qid, vec), which are to be other queries than those reported on."""
    truth = search.exact_knn(data, tuning, k).persist()
    best = {}
    for w in widths:
        fam = families.RandomProjection(d, m, w, 1)
        found = search.ring_search(search.build_index(data, fam), fam, tuning, lam, k)
        best[w] = measures.recall(found, truth, k).agg(F.avg("recall")).first()[0]
    return max(best, key=best.get)


def guarantee_rate(spark: SparkSession, n: int = 400, d: int = 16, m: int = 32, r: float = 0.5, c: float = 2.0, w: float = 2.0, seeds=range(20)) -> float:
    """Share of parameter draws in which the (R, c) decision finds a planted object at distance r among n farther than c * r."""
    import numpy as np

    hits = 0
    lam = theory.lambda_guarantee(m, n + 1, theory.rp_collision_prob(r, w), theory.rp_collision_prob(c * r, w))
    for seed in seeds:
        rng = np.random.default_rng(seed)
        x = rng.standard_normal((n + 1, d))
        x *= np.append(np.full(n, 1.1 * c * r), r)[:, None] / np.linalg.norm(x, axis=1, keepdims=True)
        data = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "obj_id long, vec array<double>")
        fam = families.RandomProjection(d, m, w, seed)
        asked = spark.createDataFrame([(0, [0.0] * d)], "qid long, vec array<double>")
        hits += search.decide(search.build_index(data, fam, rows=n + 1), fam, asked, r, c, lam).where("obj_id IS NOT NULL").count()
    return hits / len(seeds)
