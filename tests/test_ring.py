import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from ringann.functions import runs, theory
from ringann.operators import families, probe, rotation, search

Q = np.array([3, 1, 4, 1, 5, 9, 2, 6])
TOY = np.array([[3, 1, 7, 2, 8, 9, 2, 6], [3, 8, 4, 1, 5, 0, 2, 7], [0, 1, 4, 5, 8, 3, 2, 0]])
SCORES = np.array([[0.04, 0.36, 0.64], [0.25, 0.25, 1.0], [0.01, 0.81, 1.21], [0.09, 0.49, 0.90], [0.16, 0.36, 1.5]])


def test_toy():
    assert list(runs.run_lengths(TOY, Q)) == [5, 3, 2]
    s = rotation.Shard(np.arange(3), TOY)
    assert ["".join("abc"[i] for i in r) for r in s.order] == ["cab", "cab", "bca", "bac", "bca", "bca", "cab", "cab"]
    assert [list(r + 1) for r in s.link] == [[1, 2, 3], [2, 3, 1], [1, 3, 2], [1, 3, 2], [1, 2, 3], [3, 1, 2], [1, 2, 3], [1, 2, 3]]
    b = rotation.bounds(s, Q)
    assert list(b[:, 2]) == [0, 0, 3, 2, 1, 0, 1, 0] and list(b[:, 3]) == [2, 2, 1, 0, 0, 5, 4, 3]
    assert rotation.k_search(s, Q, 1) == {0: 5}


def test_narrowed_bounds_and_search_agree_with_brute_force():
    rng = np.random.default_rng(0)
    for _ in range(200):
        n, m, a = rng.integers(1, 15), rng.integers(1, 9) if rng.random() < 0.9 else rng.integers(60, 70), rng.integers(2, 4)
        codes, q = rng.integers(0, a, (n, m)), rng.integers(0, a, m)
        s = rotation.Shard(np.arange(n), codes)
        for i in range(m):
            want = sorted(range(n), key=lambda r: (tuple(np.roll(codes[r], -i)), r))
            assert list(s.order[i]) == want
        assert (rotation.bounds(s, q) == rotation.bounds(s, q, False)).all()
        lens = runs.run_lengths(codes, q)
        k = int(rng.integers(1, n + 3))
        assert sorted(rotation.k_search(s, q, k).values()) == sorted(lens)[::-1][: min(k, n)][::-1]
        slow = [max(next((d for d in range(m) if np.roll(r, -i)[d] != np.roll(q, -i)[d]), m) for i in range(m)) for r in codes]
        assert list(lens) == slow
        rows, found = rotation.scan_rows(s, q, k)
        assert dict(zip(rows.tolist(), found.tolist())) == rotation.k_search(s, q, k, ties=True)
        best = rotation.cut_ties(rotation.k_search(s, q, k, ties=True), s.ids, k)
        assert best == [(r, lens[r]) for r in sorted(range(n), key=lambda r: (-lens[r], r))][:k]


def test_perturbations_complete_and_ordered():
    found = probe.perturbations(SCORES, 10**6)
    want = set()
    for size in range(1, 6):
        for at in itertools.combinations(range(5), size):
            if all(b - a <= 2 for a, b in zip(at, at[1:])):
                want |= {tuple(zip(at, alts)) for alts in itertools.product(range(3), repeat=size)}
    assert {d for d, _ in found[1:]} == want and len(found) == len(want) + 1
    values = [s for _, s in found]
    assert all(a <= b + 1e-9 for a, b in zip(values, values[1:]))
    assert [round(v, 2) for v in values[:12]] == [0, 0.01, 0.04, 0.05, 0.09, 0.10, 0.14, 0.16, 0.17, 0.21, 0.25, 0.25]


def test_skipping_keeps_changed_bounds():
    rng = np.random.default_rng(1)
    for _ in range(300):
        n, m = rng.integers(1, 12), rng.integers(2, 8)
        codes, q = rng.integers(0, 3, (n, m)), rng.integers(0, 3, m)
        s = rotation.Shard(np.arange(n), codes)
        base, at = rotation.bounds(s, q), int(rng.integers(0, m))
        p = q.copy()
        p[at] = (p[at] + 1) % 3
        changed = np.flatnonzero((rotation.bounds(s, p) != base).any(axis=1))
        assert set(changed) <= set(probe.affected(base, at))
        alts, sc = (q[:, None] + [1, 2]) % 3, np.tile([0.1, 0.2], (m, 1))
        assert probe.search(s, q, alts, sc, 3, 1)[0] == rotation.k_search(s, q, 3)
        sc = rng.uniform(0.1, 1, (m, 2)).cumsum(axis=1)
        k, n_probes = int(rng.integers(1, n + 1)), int(rng.integers(2, 9))
        probes = [q]
        for delta, _ in probe.perturbations(sc, n_probes)[1:]:
            p = q.copy()
            for pos, alt in delta:
                p[pos] = alts[pos, alt]
            probes.append(p)
        best = np.max([runs.run_lengths(codes, p) for p in probes], axis=0)
        want = sorted(range(n), key=lambda r: (-best[r], r))[:k]
        for skip in (True, False):
            found, again = probe.search(s, q, alts, sc, k, n_probes, skip=skip, ties=True)
            assert rotation.cut_ties(found, s.ids, k) == [(r, best[r]) for r in want]
            few, many = (again, None) if skip else (few, again)
        assert few <= many


def test_formulas():
    assert theory.rp_collision_prob(1, 1) == pytest.approx(0.3687463804)
    assert theory.rp_collision_prob(2, 4) == pytest.approx(0.6095484222)
    p1, p2 = theory.rp_collision_prob(0.5, 2), theory.rp_collision_prob(1, 2)
    for m, want in ((8, 1602.8), (64, 125.5), (512, 9.8)):
        assert theory.lambda_raw(m, 2000, p1, p2) == pytest.approx(want, abs=0.05)
    for m, p, x, want in ((16, 0.5, 3, 0.554), (64, 0.5, 5, 0.590), (256, 0.5, 7, 0.599), (64, 0.8, 13, 0.519)):
        assert theory.run_cdf_exact(m, p, x) == pytest.approx(want, abs=0.006)
        assert abs(theory.run_cdf_limit(m, p, x + 1) - want) < 0.1
    assert theory.run_cdf_limit(64, 0.5, theory.run_median(64, 0.5)) == pytest.approx(0.5)
    assert theory.gamma_cdf(2, 2.0) == pytest.approx(1 - np.exp(-1))
    for m, p in ((4, 0.5), (6, 0.3)):
        total = 0.0
        for bits in itertools.product((0, 1), repeat=m):
            run = runs.run_lengths(np.array([bits]), np.ones(m, int))[0]
            total += p ** sum(bits) * (1 - p) ** (m - sum(bits)) * (run <= 2)
        assert theory.run_cdf_exact(m, p, 2) == pytest.approx(total)


def test_collision_rates():
    rng = np.random.default_rng(2)
    x = rng.standard_normal(64)
    x /= np.linalg.norm(x)
    y = x + 0.5 * (lambda v: v / np.linalg.norm(v))(rng.standard_normal(64))
    for fam, tau in ((families.RandomProjection(64, 4000, 2.0), np.linalg.norm(x - y)), (families.Hyperplane(64, 4000), np.arccos(x @ y / np.linalg.norm(y)))):
        assert np.mean(fam.codes(x[None]) == fam.codes(y[None])) == pytest.approx(fam.collision_prob(tau), abs=0.03)
    m = families.MinHash(3000)
    spread = rng.integers(0, 1 << 28, 90)
    c = m.codes(families.Sets(np.concatenate([spread[:60], spread[30:]]), np.array([0, 60, 120])))
    assert np.mean(c[0] == c[1]) == pytest.approx(1 / 3, abs=0.04)
    h = families.CrossPolytope(64, 16, rotation="hadamard")
    code, alt = h.codes(x[None]), h.alternatives(x[None], 127)
    assert all(len({code[0, j], *alt[0][0, j]}) == 128 for j in range(16))


def test_edges(spark):
    rows = [(i, [float(i), 1.0]) for i in range(5)] + [(9, None), (10, [1.0]), (11, [1.0, None]), (12, [float("nan"), 1.0])]
    data = spark.createDataFrame(rows, "obj_id long, vec array<double>")
    assert families.valid_vectors(data, 2)[1].count() == 4
    fam = families.RandomProjection(2, 1, 1.0)
    q = spark.createDataFrame([(0, [0.0, 1.0])], "qid long, vec array<double>")
    out = search.ring_search(search.build_index(data, fam, 2), fam, q, 50, 50).orderBy("rnk").collect()
    assert [r["obj_id"] for r in out] == [0, 1, 2, 3, 4]
    assert search.ring_search(search.build_index(data, fam, 2), fam, q.limit(0), 5, 5).count() == 0
    assert search.ring_search(search.build_index(data.limit(0), fam, 2), fam, q, 5, 5).count() == 0
    same = search.ring_search(search.build_index(data, fam, 2), fam, q, 50, 3, n_probes=3).count()
    assert same == 3


def test_guarantee():
    fam_p = theory.rp_collision_prob
    n, r, c, w, m = 400, 0.5, 2.0, 2.0, 32
    lam = theory.lambda_guarantee(m, n, fam_p(r, w), fam_p(c * r, w))
    rng, hits = np.random.default_rng(3), 0
    for seed in range(30):
        q = np.zeros(16)
        far = rng.standard_normal((n, 16))
        far *= 1.2 / np.linalg.norm(far, axis=1, keepdims=True)
        near = rng.standard_normal(16)
        x = np.vstack([far, near / np.linalg.norm(near) * r])
        fam = families.RandomProjection(16, m, w, seed)
        found = rotation.k_search(rotation.Shard(np.arange(n + 1), fam.codes(x)), fam.codes(q[None])[0], lam)
        hits += n in found
    assert hits / 30 >= 0.25


def test_document_recall(spark):
    from ringann.functions import measures
    from ringann.sources import workloads

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    data, q = workloads.split_queries(workloads.hashed_documents(docs, 128).persist(), 10)
    fam = families.RandomProjection(128, 64, 1.0, 1)
    index = search.build_index(data, fam)
    truth = search.exact_knn(data, q, 10)
    few, many = (measures.recall(search.ring_search(index, fam, q, lam, 10), truth, 10).agg(F.avg("recall")).first()[0] for lam in (10, 60))
    assert many >= few and many > 0.4


def test_stream_equals_batch(spark, tmp_path):
    from ringann.streaming import streams

    src = spark.read.parquet("/root/testdata/sf0.001/events.parquet")
    src.write.parquet(str(tmp_path / "in"))
    stream = streams.event_profiles(spark.readStream.schema(src.schema).parquet(str(tmp_path / "in")))
    stream.writeStream.format("memory").queryName("profiles").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    want = {tuple(map(str, r)) for r in streams.event_profiles(src).collect()}
    assert {tuple(map(str, r)) for r in spark.table("profiles").collect()} == want


def test_plateaus_of_equal_strings():
    from ringann.operators import rotation

    codes = np.repeat(np.array([[1, 2, 3], [1, 2, 4], [9, 9, 9]], np.int32), 300, axis=0)
    s = rotation.Shard(np.arange(900), codes)
    rows, lens = rotation.k_search_rows(s, np.array([1, 2, 3], np.int32), 5, ties=True)
    assert sorted(rows) == list(range(300)) and set(lens) == {3} and not s.seen.any()
    assert len(rotation.k_search(s, np.array([1, 2, 3], np.int32), 5)) == 5
    rows, lens = rotation.k_search_rows(s, np.array([1, 2, 3], np.int32), 301, ties=True)
    assert len(rows) == 600 and sorted(set(lens)) == [2, 3]


def test_ratio_of_angles_that_are_rounding_noise(spark):
    from ringann.functions import measures

    truth = spark.createDataFrame([(1, 1, 2e-8), (1, 2, 0.5)], "qid long, rnk int, dist double")
    found = spark.createDataFrame([(1, 1, 0.0), (1, 2, 1.0)], "qid long, rnk int, dist double")
    row = measures.overall_ratio(found, truth).first()
    assert row["ratio"] == 1.5 and row["n_zero"] == 0


def test_document_queries_ask_all_documents(spark):
    from ringann.plans import queries
    from ringann.sources import workloads

    sf = "/root/testdata/sf0.001"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    asked = {r[0] for r in workloads.hashed_documents(docs, 128).select("obj_id").collect()}
    assert {r["qid"] for r in queries.documents_dups(spark, sf).collect()} == asked
    labelled = {r[0] for r in labels.where("quality IS NOT NULL").select("doc_id").collect()}
    voted = {r["qid"] for r in queries.label_vote(spark, sf).collect()}
    assert voted <= asked - labelled and len(voted) > 0.9 * len(asked - labelled)


def test_recall_of_document_queries(spark):
    from ringann.functions import measures
    from ringann.plans import queries
    from ringann.sources import workloads

    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    data = workloads.hashed_documents(docs, 128).persist()
    items = workloads.hashed_documents(spark.read.parquet(f"{sf}/benchmark.parquet"), 128, "item_id")
    cases = ((queries.documents_dups, data, 10, "euclidean", True), (queries.contamination, items, 5, "angular", False))
    for query, asked, k, metric, exclude_self in cases:
        truth = search.exact_knn(data, asked.withColumnRenamed("obj_id", "qid"), k, metric, exclude_self)
        assert measures.recall(query(spark, sf), truth, k).agg(F.avg("recall")).first()[0] >= 0.9


def test_entry_points_on_ordinary_trouble(spark):
    """Unusable vectors, empty sides, repeated ids and ties, in every search."""
    from ringann.operators import baselines

    rows = [(i % 6, [float(i), 1.0]) for i in range(8)] + [(20, None), (21, [1.0]), (22, [0.0, 0.0])]
    data = spark.createDataFrame([(i, v, "x") for i, v in rows], "obj_id long, vec array<double>, dist string")
    q = spark.createDataFrame([(0, [0.0, 1.0]), (1, None), (2, [2.0])], "qid long, vec array<double>")
    rp, cp, hp = families.RandomProjection(2, 4, 1.0), families.CrossPolytope(2, 4), families.Hyperplane(2, 4)
    searches = [
        lambda a, b: search.ring_search(search.build_index(a, rp, 3), rp, b, 20, 3), lambda a, b: search.ring_search(search.build_index(a, rp, 3), rp, b, 20, 3, n_probes=4, verify="shard"),
        lambda a, b: search.ring_search(search.build_index(a, hp, 3), hp, b, 20, 3), lambda a, b: baselines.static_concat(a, rp, b, 1, 4, 3), lambda a, b: baselines.multiprobe_static(a, cp, b, 1, 4, 3, 2),
        lambda a, b: baselines.collision_count(a, rp, b, 1, 3, 2, 2), lambda a, b: baselines.query_aware_count(a, b, 2, 4, 2.0, 2, 3, 2.0, 3), lambda a, b: baselines.projected_incremental(a, b, 2, 2, 5, 3, 2.0, 0.5),
        lambda a, b: baselines.query_aware_blocked(a, b, 2, 4, 4.0, 1, 3, 2, 2, 2, 4), lambda a, b: baselines.prefix_widening(a, rp, b, 2, 2, 3, 2), lambda a, b: search.exact_knn(a.where("size(vec) = 2"), b.where("size(vec) = 2"), 3, "angular"),
    ]
    for f in searches:
        found = f(data, q)
        assert {r["qid"] for r in found.collect()} <= {0} and not {r["obj_id"] for r in found.collect()} & {20, 21}
        assert f(data.limit(0), q).count() == 0 and f(data, q.limit(0)).count() == 0
    near = search.ring_search(search.build_index(data, rp, 3), rp, q, 20, 3).orderBy("rnk").collect()
    assert [(r["obj_id"], r["dist"]) for r in near] == [(0, 0.0), (22, 1.0), (1, 1.0)] or [(r["obj_id"], r["dist"]) for r in near] == [(0, 0.0), (1, 1.0), (22, 1.0)]


def test_unknown_metric_raises():
    with pytest.raises(ValueError):
        search.distances("cosine", np.zeros((1, 2)), np.zeros(2))
    sets = families.Sets(np.array([1, 2, 3, 5]), np.array([0, 3, 3, 4]))
    assert list(search.distances("jaccard", sets, np.array([1, 2, 9]))) == [0.5, 1.0, 1.0]
    assert list(search.distances("jaccard", sets[[1]], np.array([], np.int64))) == [0.0]


def test_bound_properties():
    """Among sorted strings the middle one shares as much with any other as the less of the outer two; dropping shared symbols keeps the order."""
    rng = np.random.default_rng(5)
    lcp = lambda a, b: next((i for i, (x, y) in enumerate(zip(a, b)) if x != y), len(a))
    for _ in range(2000):
        m = int(rng.integers(1, 8))
        a, b, c = sorted(tuple(rng.integers(0, 3, m)) for _ in range(3))
        for q in (a, c, tuple(rng.integers(0, 3, m))):
            if a <= b < c:
                assert lcp(b, c) >= min(lcp(a, c), lcp(b, c)) and lcp(a, b) >= lcp(a, c) or a == b
        q = b
        s = min(lcp(a, q), lcp(c, q))
        for cut in range(s + 1):
            assert a[cut:] + a[:cut] <= q[cut:] + q[:cut] or a[cut:] == q[cut:]


def test_narrowed_search_takes_fewer_steps(spark):
    from ringann.plans import queries

    for r in queries.search_work(spark, "/root/testdata/sf0.01").collect():
        assert 0 < r["narrowed"] <= r["simple"] and r["candidates"] == queries.LAM


def test_query_blocks_and_shards_do_not_change_results(spark):
    from ringann.plans import queries
    from ringann.plans.settings import RP

    data, q = queries._emb(spark, "/root/testdata/sf0.01")
    one = search.ring_search(search.build_index(data, RP, rows=1), RP, q, 20, 5)
    many = search.ring_search(search.build_index(data, RP, 50), RP, q, 20, 5, query_block=3)
    assert sorted(one.collect()) == sorted(many.collect())


def test_index_survives_writing_and_compaction(spark, tmp_path):
    from ringann.plans import queries
    from ringann.plans.settings import RP
    from ringann.streaming import streams

    data, q = queries._emb(spark, "/root/testdata/sf0.001")
    base, path, delta = data.where("obj_id % 3 > 0"), str(tmp_path / "index"), str(tmp_path / "delta")
    search.write_index(search.build_index(base, RP, 100), path)
    data.where("obj_id % 3 = 0").write.parquet(str(tmp_path / "in"))
    stream = streams.stream_ingest(spark.readStream.schema("obj_id long, vec array<double>").parquet(str(tmp_path / "in")), delta, str(tmp_path / "c1"))
    stream.processAllAvailable(), stream.stop()
    late = streams.read_delta(spark, delta)
    truth = search.exact_knn(data, q, 5)
    cols = ["qid", "rnk", "obj_id"]
    both = streams.search_with_delta(search.read_index(spark, path), late, RP, q, 1000, 5)
    assert sorted(both.select(cols).collect()) == sorted(truth.select(cols).collect())
    assert streams.compact(spark, delta, RP, path, 100) == data.where("obj_id % 3 = 0").count()
    index = search.read_index(spark, path)
    stats = search.index_stats(index).first()
    assert stats["objects"] == data.count() and index.select("shard").distinct().count() == stats["shards"]
    assert sorted(search.ring_search(index, RP, q, 1000, 5).select(cols).collect()) == sorted(truth.select(cols).collect())
    assert streams.compact(spark, delta, RP, path, 100) == 0 and streams.read_delta(spark, delta).count() == 0
    q.write.parquet(str(tmp_path / "asked"))
    answers = streams.stream_search(spark.readStream.schema("qid long, vec array<double>").parquet(str(tmp_path / "asked")), index, RP, 1000, 5, str(tmp_path / "out"), str(tmp_path / "c2"))
    answers.processAllAvailable(), answers.stop()
    assert sorted(spark.read.parquet(str(tmp_path / "out")).select(cols).collect()) == sorted(truth.select(cols).collect())


def test_drift_alarms(spark, tmp_path):
    from ringann.streaming import streams

    rows = [(1, i, f"2024-01-01 00:00:{i:02d}", 100.0 if i == 7 else 1.0) for i in range(10)] + [(2, 50, "2024-01-01 00:00:00", 100.0)]
    spark.createDataFrame(rows, "user_id long, event_id long, ts string, value double").withColumn("ts", F.to_timestamp("ts")).coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema("user_id long, event_id long, ts timestamp, value double").parquet(str(tmp_path / "in"))
    streams.drift_alarms(stream).writeStream.format("memory").queryName("alarms").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    assert [(r["user_id"], r["event_id"], r["mean"]) for r in spark.table("alarms").collect()] == [(1, 7, 1.0)]


def test_vector_formats(spark, tmp_path):
    import struct

    from ringann.sources.tables import read_vectors

    rows = [(i, [float(i), 0.5, -1.0]) for i in range(20)]
    df = spark.createDataFrame(rows, "obj_id long, vec array<double>")
    for fmt in ("parquet", "orc", "json"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        assert sorted((r[0], list(r[1])) for r in read_vectors(spark, str(tmp_path / fmt), fmt).collect()) == rows
    df.select(F.concat_ws(",", F.col("obj_id").cast("string"), F.array_join(F.transform("vec", lambda x: x.cast("string")), ","))).write.text(str(tmp_path / "csv"))
    assert sorted((r[0], list(r[1])) for r in read_vectors(spark, str(tmp_path / "csv"), "csv").collect()) == rows
    (tmp_path / "x.fvecs").write_bytes(b"".join(struct.pack("<i3f", 3, *v) for _, v in rows))
    assert sorted((r[0], list(r[1])) for r in read_vectors(spark, str(tmp_path / "x.fvecs"), "fvecs").collect()) == rows


def test_joins(spark):
    from ringann.operators import joins

    a = spark.createDataFrame([(1, "u", 5), (2, "u", 1), (3, None, 5), (4, "v", 9)], "id int, k string, t int")
    b = spark.createDataFrame([("u", 2, "x"), ("u", 5, "y"), ("u", 6, "z"), (None, 1, "n"), ("v", None, "m")], "k string, t int, val string")
    assert {(r["id"], r["val"]) for r in joins.as_of_join(a, b, "k", "t", ["val"]).collect()} == {(1, "y"), (2, None), (3, None), (4, None)}
    x = spark.createDataFrame([(i, v) for i, v in enumerate([0.0, 1.0, 2.5, None])], "i int, a double")
    y = spark.createDataFrame([(i, v) for i, v in enumerate([0.5, 3.0, None])], "j int, b double")
    assert {(r["i"], r["j"]) for r in joins.band_join(x, y, "a", "b", 0.5).collect()} == {(0, 0), (1, 0), (2, 1)}


def test_sql_functions(spark):
    from ringann.functions import sqlfn

    sqlfn.register_all(spark)
    assert spark.sql("SELECT ring_run_len(array(1,2,3,4), array(1,9,3,4)), ring_equal_positions(array(1,2), array(1,3)), ring_run_len(NULL, array(1))").first()[:] == (3, 1, None)
    assert [list(r["s"]) for r in spark.sql("SELECT * FROM ring_rotations(array(1,2,3)) ORDER BY rot").collect()] == [[1, 2, 3], [2, 3, 1], [3, 1, 2]]
    got = spark.sql("SELECT * FROM ring_perturbations(array(array(0.04D, 0.36D), array(0.25D, 0.5D)), 4) ORDER BY probe_no").collect()
    assert [round(r["score"], 2) for r in got] == [0, 0.04, 0.25, 0.29] and list(got[3]["positions"]) == [0, 1]


def test_experiments(spark):
    from ringann.functions import measures
    from ringann.plans import experiments, queries
    from ringann.sources import workloads

    data, q = workloads.split_queries(workloads.embeddings(spark, "/root/testdata/sf0.001"), 50)
    for metric in ("euclidean", "angular"):
        rows = experiments.time_recall(spark, data, q, 64, metric, ms=(8,), lams=(20,), concat=((2, 4),), thresholds=(2,), runs=2).persist()
        assert rows.where("seconds <= 0 OR recall < 0 OR ratio < 0.999999").count() == 0 and rows.where("method = 'ring' AND build_seconds > 0 AND index_bytes > 0").count() == 2
        assert measures.summarize(rows).where("runs = 2").count() == rows.count() / 2
    rates = [r["recall"] for r in experiments.sensitivity_to_k(spark, data, q, 64, ks=(1, 10), m=8, lam=1000).collect()]
    assert rates == [1.0, 1.0]
    assert experiments.tune_width(data, data.where("obj_id % 50 = 25").withColumnRenamed("obj_id", "qid"), 64, (2.0,), m=8) == 2.0
    assert experiments.guarantee_rate(spark, 60, 8, 8, seeds=range(4)) >= 0.25
    assert len(queries.QUERIES) - len(queries.ORACLES) == 5


def test_stand_ins(spark):
    from ringann.sources import workloads

    for name in workloads.STAND_INS:
        vecs, d = workloads.stand_in(spark, "/root/testdata/sf0.001", name)
        rows = vecs.collect()
        assert len(rows) > 20 and all(len(r["vec"]) == d for r in rows)
        if name in ("wide", "text", "codes"):
            assert all(np.linalg.norm(r["vec"]) == pytest.approx(1) for r in rows)


def test_result_sets_are_disjoint(spark):
    from ringann.plans import queries

    rows = queries.QUERIES["result_sets"](spark, "/root/testdata/sf0.01").collect()
    assert len({(r["qid"], r["obj_id"]) for r in rows}) == len(rows)
    sides = [r["side"] for r in rows]
    assert sides.count("missed") == sides.count("wrong") and sides.count("hit") + sides.count("missed") == 100


def test_shards_without_the_query_send_no_extra_candidate(spark):
    rng = np.random.default_rng(3)
    x = rng.standard_normal((90, 4))
    data = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(5, x[5].tolist())], "obj_id long, vec array<double>")
    family = families.RandomProjection(4, 6, 2.0, seed=1)
    codes, ids = family.codes(np.concatenate([x, x[5:6]])), np.array([*range(90), 5])
    got = search.ring_search(search.build_index(data, family, shard=F.col("obj_id") % 3), family, data.where("obj_id = 5").limit(1).withColumnRenamed("obj_id", "qid"), 4, 2, verify="shard", exclude_self=True)
    lens, cands = runs.run_lengths(codes, codes[5]), []
    for part in range(3):
        cands += sorted((r for r in range(91) if ids[r] % 3 == part and ids[r] != 5), key=lambda r: (-lens[r], ids[r]))[:5]
    want = sorted(cands, key=lambda r: np.linalg.norm(x[r] - x[5]))[:2]
    assert [r["obj_id"] for r in got.orderBy("rnk").collect()] == want


def test_blocks_are_halved_at_exact_medians_as_often_as_asked(spark):
    from ringann.operators import baselines

    rng = np.random.default_rng(5)
    x = np.concatenate([rng.standard_normal((301, 2)), np.full((50, 2), 0.25), np.zeros((50, 2))])
    data = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "obj_id long, vec array<double>")
    block = np.zeros(len(x), int)
    for level in range(2):
        cuts = {b: np.sort(x[block == b, level])[(np.count_nonzero(block == b) + 1) // 2 - 1] for b in set(block)}
        block = np.array([2 * b + (v > cuts[b]) for b, v in zip(block, x[:, level])])
    assert {r["obj_id"]: r["block"] for r in baselines.median_blocks(data, 2, 2).collect()} == dict(enumerate(block))
    # All objects lie near enough; with two halvings and all four blocks asked the search is the exact one, whatever the leaf.
    q = data.where("obj_id < 3").withColumnRenamed("obj_id", "qid")
    cols = ["qid", "rnk", "obj_id"]
    got = baselines.query_aware_blocked(data, q, 2, 2, 1e9, 1, 4, 10, 2, 2, 4, exclude_self=True, halvings=2)
    assert sorted(got.select(cols).collect()) == sorted(search.exact_knn(data, q, 4, exclude_self=True).select(cols).collect())


def test_standardized_values_are_exact_to_the_last_bits(spark):
    from ringann.sources import workloads

    # 0.1 has no exact double and a plain sum of many drifts; the far values make the deviation small beside the mean.
    df = spark.range(0, 400_000, 1, 1).select(F.col("id").alias("obj_id"), (F.lit(1e6) + F.pmod("id", F.lit(10)) * 0.1).alias("a"), F.lit(3.7).alias("b"))
    got = {round(r["k"]): r["v"] for r in workloads.standardize(df, ["a", "b"]).groupBy((F.col("obj_id") % 10).alias("k")).agg(F.first(F.col("vec")[0]).alias("v")).collect()}
    from fractions import Fraction

    x = [Fraction(1e6 + i * 0.1) for i in range(10)]
    mean = sum(x) / 10
    sd = float(sum((v - mean) ** 2 for v in x) / 10) ** 0.5
    assert all(abs(got[i] - float(x[i] - mean) / sd) < 1e-9 for i in range(10))
    assert workloads.standardize(df, ["b"]).where("vec[0] <> 0").count() == 0


def test_scans_of_probes_and_of_joined_shards_give_what_the_search_gives():
    rng = np.random.default_rng(8)
    for m in (5, 8, 12):
        codes, q = rng.integers(-2, 2, (400, m)).astype(np.int32), rng.integers(-2, 2, m).astype(np.int32)
        ids = np.arange(400) // 2
        alts = np.stack([q + 1, q - 1], axis=1).astype(np.int32)
        scores = np.sort(rng.random((m, 2)), axis=1)
        whole = rotation.Shard(ids, codes)
        rows, lens, _ = probe.search_rows(whole, q, alts, scores, 30, m + 1, ties=True)
        want = [(ids[r], n) for r, n in zip(*rotation.cut_rows(rows, lens, ids, 30))]  # equal ids in any order
        halves = [(rotation.Shard(ids[at], codes[at]), codes[at]) for at in (np.arange(400) % 4 < 2, np.arange(400) % 4 >= 2)]
        one, vecs = search._as_one(halves)
        assert (vecs == one.codes).all() and (one.ids == ids).all() and one.least == 200
        for s in (whole, one):
            assert [(ids[r], n) for r, n in zip(*s.scan(probe.strings(q, alts, scores, m + 1), 30))] == want


def test_sql_functions_take_whole_columns():
    import pyarrow as pa

    from ringann.functions import sqlfn

    rng = np.random.default_rng(2)
    for m in (3, 8, 20, 70):
        a, b = rng.integers(0, 2, (40, m)), rng.integers(0, 2, (40, m))
        left, right = pa.array([*a.tolist(), None, [], a[0].tolist()]), pa.array([*b.tolist(), b[0].tolist(), [], None])
        assert sqlfn.run_len(left, right).to_pylist() == [*(int(runs.run_lengths(x[None], y)[0]) for x, y in zip(a, b)), None, 0, None]
        assert sqlfn.equal_positions(left, right).to_pylist() == [*(a == b).sum(axis=1).tolist(), None, 0, None]
    calls = []
    sqlfn._pairs(pa.array(a.tolist()), pa.array(b.tolist()), lambda x, y: calls.append(len(x)) or np.zeros(len(x)))
    assert calls == [40]


def test_jaccard_of_a_block_is_that_of_each_query():
    import pyarrow as pa

    rng = np.random.default_rng(4)
    lists = [rng.integers(0, 30, rng.integers(0, 25)).tolist() for _ in range(60)]
    sets = families.Sets.of(pa.array([[9, 9], *lists], pa.list_(pa.int64())).slice(1))
    assert [sets[i].tolist() for i in range(60)] == [sorted(set(v)) for v in lists]
    q = sets[np.array([0, 5, 5, 59])]
    got = search.jaccard_distances(sets, q)
    assert got.shape == (4, 60) and all((got[j] == search.distances("jaccard", sets, q[j])).all() for j in range(4))
    assert search.jaccard_distances(sets, sets[np.zeros(0, np.int64)]).shape == (0, 60)


@pytest.mark.parametrize("metric, m, part", [("euclidean", 12, 0.3), ("angular", 7, 0.5), ("euclidean", 70, 0.15)])
def test_nearest_candidates_of_a_block_are_those_of_each_query(metric, m, part):
    rng = np.random.default_rng(m)
    x = rng.standard_normal((400, 5))
    x[::7], x[300:340] = x[0], x[20]  # copies, more of some than are asked for
    codes = np.where(rng.random((400, m)) < 0.6, np.floor(x @ rng.standard_normal((5, m))), 0).astype(np.int32)
    codes[::7], codes[300:340] = codes[0], codes[20]
    ids, best = np.arange(400) * 3, 4
    asked = np.array([0, 3, 7, 20, 310, 399, 150, 42])
    shards = [np.flatnonzero(np.arange(400) % 3 == i) for i in range(3)]
    near, got = np.full((len(asked), best), np.inf), [[] for _ in asked]
    for at in shards:
        s = rotation.Shard(ids[at], codes[at])
        least = round(part * len(at))
        lo, hi = np.searchsorted(s.ids, ids[asked]), np.searchsorted(s.ids, ids[asked], "right")
        qs, rows, lens, dist = search._Near(s, x[at], metric, best).ask(x[asked], codes[asked], lo, hi, least, near[:, -1])
        assert not hasattr(s, "kinds")  # no query was compared with all strings
        for j, q in enumerate(asked):
            run = runs.run_lengths(s.codes, codes[q])
            want = sorted((r for r in range(s.n) if at[r] != q), key=lambda r: (-run[r], s.ids[r]))[:least]
            far = dict(zip(want, search.distances(metric, x[at][want], x[q]).round(7)))
            want = [r for r in sorted(want, key=lambda r: (far[r], s.ids[r]))[:best] if far[r] <= near[j, -1] + 1e-7]
            mine = qs == j
            assert rows[mine].tolist() == want and lens[mine].tolist() == run[want].tolist()
            assert dist[mine] == pytest.approx([far[r] for r in want], abs=1e-6)
            near[j] = np.sort(np.concatenate([near[j], dist[mine]]))[:best]


@pytest.mark.parametrize("metric", ["euclidean", "angular"])
def test_tiles_give_the_nearest_rows(metric):
    rng = np.random.default_rng(5)
    x = np.concatenate([rng.standard_normal((700, 20)) * 0.1 + c for c in np.eye(20)[:3] * 4])
    x[::9], x[900:960] = x[0], x[20]  # copies, more of some than are asked for
    ids = np.arange(len(x)) * 3
    ids[1501] = ids[1500]  # two rows of one id
    asked, best = np.array([0, 9, 25, 901, 1500, 2099]), 8
    tiles = search._Tiles(ids, x, metric, best)
    assert len(tiles.rows) > 1 and max(map(len, tiles.rows)) <= tiles.TILE
    for own in (True, False):
        at, rows, dist = tiles.nearest(ids[asked], x[asked], own)
        for j, q in enumerate(asked):
            far = search.distances(metric, x, x[q])
            want = [r for r in np.lexsort((ids, far.round(7))) if not own or ids[r] != ids[q]][:best]
            assert dist[at == j] == pytest.approx(far[want], abs=1e-6)
            assert metric == "angular" or rows[at == j].tolist() == want


def test_nearest_first_is_the_whole_search(spark):
    """Also for queries that have fewer candidates among the listed rows than asked."""
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.standard_normal((150, 6)), rng.standard_normal((150, 6)) * 0.05 + 2])
    x[200:240] = x[200]  # copies
    data = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "obj_id long, vec array<double>").persist()
    family = families.RandomProjection(6, 12, 0.5, seed=2)
    index = search.build_index(data, family, 80, rows=300).persist()
    queries = data.withColumnRenamed("obj_id", "qid")
    rows = lambda **how: sorted(map(tuple, search.ring_search(index, family, queries, 12, 4, verify="shard", **how).collect()))
    for own in (True, False):
        whole = rows(exclude_self=own, listed=0)
        assert rows(exclude_self=own, listed=1) == whole == rows(exclude_self=own, listed=3) and len(whole) == 1200
    blocks = search.query_blocks(queries, family.points, False, family, hint=False)
    _, left = search._nearest_first(index, family, blocks, 15, 4, 4, "euclidean", True)
    assert left is not None and 0 < left.count() < 300
    twice = search.query_blocks(queries.union(queries), family.points, False, family, hint=False)
    assert search._nearest_first(index, family, twice, 15, 4, 4, "euclidean", True) is None


def _against_sql(spark, name, sf="/root/testdata/sf0.001", **tables):
    """Rows of a query and of its SQL, over the tables of sf with some put in their place."""
    import duckdb

    from ringann.plans import queries

    con = duckdb.connect()
    for table in ("lineitem", "embeddings"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{tables.get(table, f'{sf}/{table}.parquet')}'")
    want = con.execute(queries.ORACLES[name]).to_arrow_table()
    got = queries.QUERIES[name](spark, sf)
    assert got.columns == want.column_names
    plain = lambda row: tuple(round(x, 9) if isinstance(x, float) else x for x in row)
    rows = sorted((plain(r) for r in got.collect()), key=repr)
    assert rows == sorted((plain(r.values()) for r in want.to_pylist()), key=repr) and rows
    return got, rows


def _reads(df, table):
    return any(f.endswith(f"/{table}.parquet") for f in df.inputFiles())


def test_lambda_table_reads_line_items(spark):
    got, rows = _against_sql(spark, "lambda_table")
    assert _reads(got, "lineitem") and len(rows) == 5 * len({r[0] for r in rows})


def test_alpha_table_reads_line_items(spark):
    got, rows = _against_sql(spark, "alpha_table")
    assert _reads(got, "lineitem") and len(rows) == 3 * len({r[0] for r in rows})


def test_complexity_table_reads_line_items(spark):
    got, rows = _against_sql(spark, "complexity_table")
    assert _reads(got, "lineitem") and len(rows) == 5 * len({r[0] for r in rows})
    assert theory.complexity_rows(10000.0, 64.0, 0.5, 64.0)[2][1:4] == (0.0, 1.0, 10000.0)


def test_concatenation_reads_line_items(spark):
    got, rows = _against_sql(spark, "concatenation")
    assert _reads(got, "lineitem") and len(rows) == 12 * len({r[0] for r in rows})


def test_cp_quality_reads_embeddings(spark):
    got, rows = _against_sql(spark, "cp_quality")
    assert _reads(got, "embeddings") and all(0 < r[2] < 1 for r in rows)


def test_hash_cost_reads_embeddings(spark):
    got, rows = _against_sql(spark, "hash_cost")
    assert _reads(got, "embeddings") and {r[:2] for r in rows} == {(f, 64) for f in ("random_projection", "cross_polytope", "bit_sampling")}


def test_run_distribution_reads_embeddings(spark):
    got, rows = _against_sql(spark, "run_distribution")
    assert _reads(got, "embeddings") and all(r[3] == r[4] == 1 for r in rows if r[1] == 8) and len(rows) == 90


def test_grids_of_constants_are_no_query():
    import __spark_entry__ as e

    assert "grids" not in e.queries() and "grids" not in e.oracle_sql()
    assert all(theory.grid(name) for name in theory.GRIDS)  # the grids themselves stay


def test_pareto_reads_embeddings(spark):
    got, rows = _against_sql(spark, "pareto")
    assert _reads(got, "embeddings") and {r[0] for r in rows} == {"ring", "projected_incremental"}


def test_budget_curve_reads_embeddings(spark):
    got, rows = _against_sql(spark, "budget_curve")
    assert _reads(got, "embeddings") and {r[0] for r in rows} == {"ring", "projected_incremental"}


def test_budget_curve_asks_every_embedding(spark, tmp_path):
    some = spark.read.parquet("/root/testdata/sf0.001/embeddings.parquet").where("vec_id % 50 <> 0")
    some.write.parquet(f"{tmp_path}/embeddings.parquet")
    _, rows = _against_sql(spark, "budget_curve", str(tmp_path), embeddings=f"{tmp_path}/embeddings.parquet/*.parquet", lineitem="/root/testdata/sf0.001/lineitem.parquet")
    assert {r[0] for r in rows} == {"ring", "projected_incremental"}


@pytest.mark.parametrize("part", [search.CELL_BYTES, 4000])
def test_many_queries_meet_data_in_cells(spark, monkeypatch, part):
    from ringann.operators import baselines

    rng = np.random.default_rng(5)
    vecs = np.concatenate([rng.standard_normal((150, 6)), np.ones((40, 6)), rng.integers(0, 2, (60, 6))])
    vecs[3, 0], vecs[160, 1] = 1e100, 1e-30
    data = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(rng.permutation(250), vecs)], "obj_id long, vec array<double>").persist()
    queries = data.select(F.col("obj_id").alias("qid"), "vec")
    asks = [
        lambda q: search.exact_knn(data, q, 5, exclude_self=True), lambda q: search.exact_knn(data, q, 300),
        lambda q: baselines.projected_incremental(data, q, 6, 2, 30, 4, exclude_self=True), lambda q: baselines.projected_incremental(data, q, 6, 2, 30, 4, 1.5, 0.8),
        lambda q: baselines.projected_incremental(data, q.union(q), 6, 2, 30, 4),
    ]
    for ask in asks:
        plain = sorted(map(tuple, ask(queries).collect()))
        with monkeypatch.context() as m:
            m.setattr(search, "CELL_QUERIES_FROM", 0), m.setattr(search, "CELL_BYTES", part), m.setattr(search, "CELL_PIECE", 40), m.setattr(search, "CELL_FOUND", 2000)
            assert sorted(map(tuple, ask(queries).collect())) == plain


def test_acceleration_reads_embeddings(spark):
    got, rows = _against_sql(spark, "acceleration")
    assert _reads(got, "embeddings") and dict(rows)["ring"] == 0


def test_rollup_report_reads_embeddings(spark):
    got, rows = _against_sql(spark, "rollup_report")
    assert _reads(got, "embeddings") and sorted(r[4] for r in rows) == [0] * 5 + [1, 1, 3]


@pytest.mark.parametrize("n", [1, 25, 140])
def test_every_cell_has_a_partition_of_its_own(spark, n):
    keys = spark.createDataFrame([(k,) for k in search._cell_keys(spark, n)], "cell int").repartition(n, "cell")
    assert keys.groupBy(F.spark_partition_id()).count().where("count = 1").count() == n
