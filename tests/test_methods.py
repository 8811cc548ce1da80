"""Worked examples, exact baselines, draws, guarantees and edge cases of the matrix methods."""

from __future__ import annotations

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from tallgram.functions.draws import unit_draw
from tallgram.operators import accuracy, cost, gram, least_squares, matrix, sampling, similarity, spectral
from tallgram.operators.norms import column_norms
from tallgram.plans import planner
from tallgram.sources import workloads

SMALL = "/root/testdata/sf0.001"


def table(df, *keys):
    return {tuple(r[k] for k in keys): r for r in df.collect()}


def make(spark, rows):
    return spark.createDataFrame([(r, [(c, float(v)) for c, v in e]) for r, e in rows], "row_id long, entries array<struct<col:int,val:double>>")


def test_tiny_norms_and_gram(tiny):
    assert {r["col"]: r["sumsq"] for r in column_norms(tiny).collect()} == {0: 3, 1: 3, 2: 2}
    g = table(gram.exact_gram(tiny), "i", "j")
    assert {k: r["dot"] for k, r in g.items()} == {(0, 1): 2, (0, 2): 1, (1, 2): 2}
    c = {k: round(r["cos"], 6) for k, r in table(gram.exact_cosines(tiny), "i", "j").items()}
    assert c == {(0, 1): 0.666667, (0, 2): 0.408248, (1, 2): 0.816497}
    assert cost.emissions(tiny, "exact").first()[:] == ("exact", 5, 3, 2)


def test_tiny_spectrum(tiny):
    norms = column_norms(tiny)
    upper = gram.gram_from_cosines(gram.exact_cosines(tiny), norms)
    values, vectors = spectral.spectral_factors(upper, 3)
    assert [round(r["sigma"], 6) for r in values.orderBy("rank").collect()] == [2.473667, 1.252347, 0.559107]
    assert vectors.count() == 9
    u = spectral.left_factor(tiny, values, vectors, 3)
    a = np.array([[1, 1, 0], [1, 1, 1], [0, 1, 1], [1, 0, 0]], dtype=float)
    sigma = np.array([r["sigma"] for r in values.orderBy("rank").collect()])
    v, w = np.zeros((3, 3)), np.zeros((4, 3))
    for r in vectors.collect():
        v[r["col"], r["rank"] - 1] = r["weight"]
    for r in u.collect():
        w[r["row_id"], r["rank"] - 1] = r["weight"]
    assert np.allclose(w * sigma @ v.T, a)


def test_tiny_draws(spark, tiny):
    pairs = gram.all_pairs(tiny).select("row_id", "i", "j", F.round(unit_draw(7, "row_id", "i", "j", kind="md5"), 6).alias("u"))
    assert {k: r["u"] for k, r in table(pairs, "row_id", "i", "j").items()} == {(0, 0, 1): 0.324487, (1, 0, 1): 0.777868, (1, 0, 2): 0.411901, (1, 1, 2): 0.387433, (2, 1, 2): 0.339785}
    low = table(sampling.sampled_cosines(tiny, 1.0, 7, draw="md5"), "i", "j")
    assert {k: round(r["cos"], 6) for k, r in low.items()} == {(0, 1): 1.0, (1, 2): 2.0}
    high = table(sampling.sampled_cosines(tiny, 2.5, 7, draw="md5"), "i", "j")
    assert {k: (round(r["cos"], 6), r["is_exact"]) for k, r in high.items()} == {(0, 1): (0.8, False), (0, 2): (0.408248, True), (1, 2): (0.816497, True)}
    assert cost.expected_emissions(tiny, 1.0).first()["expected"] == pytest.approx(1.891412, abs=1e-6)
    assert planner.shuffle_bound(3, 3, 1.0) == 9


def test_staged_budget_is_smaller_when_one_norm_is_below_the_root():
    assert planner.effective_gamma(100, 3, 100, "pair") == 100
    assert planner.effective_gamma(100, 3, 100, "staged") == 30


@pytest.mark.parametrize("kind", ["xxhash64", "md5"])
def test_draws_are_uniform(spark, kind):
    u = np.array([r[0] for r in spark.range(4000).select(unit_draw(3, "id", kind=kind)).collect()])
    assert 0 <= u.min() and u.max() < 1 and abs(u.mean() - 0.5) < 0.02 and abs(u.std() - 1 / math.sqrt(12)) < 0.01


def test_unknown_draw(spark):
    with pytest.raises(ValueError):
        unit_draw(1, "id", kind="md4")


def test_baselines_agree(spark):
    m = workloads.matrix(spark, SMALL, "w4")
    want = {(r["i"], r["j"]): r["dot"] for r in gram.exact_gram(m).collect()}
    t = matrix.to_triplets(m)
    for other in (gram.exact_gram(m, combine=False), gram.exact_gram_join(t), gram.exact_gram_join(t, "shuffle_hash"), gram.exact_gram_blocks(m, 25, block=7)):
        assert {(r["i"], r["j"]): r["dot"] for r in other.collect()} == want


@pytest.mark.parametrize("name", ["w4", "w4c", "w5", "w3"])
def test_unbounded_budget_is_exact(spark, name):
    m = workloads.matrix(spark, SMALL, name)
    want = table(gram.exact_cosines(m), "i", "j")
    for method in ("pair", "staged", "thinned"):
        got = table(sampling.estimate(m, method, 1e12), "i", "j")
        assert got.keys() == want.keys() and all(abs(got[k]["cos"] - want[k]["cos"]) < 1e-9 for k in want)


def test_result_depends_on_seed_alone(spark):
    m = workloads.matrix(spark, SMALL, "w4")
    one = {k: r["cos"] for k, r in table(sampling.sampled_cosines(m.repartition(7), 5.0, 1), "i", "j").items()}
    two = {k: r["cos"] for k, r in table(sampling.sampled_cosines(m.coalesce(1), 5.0, 1), "i", "j").items()}
    other = {k: r["cos"] for k, r in table(sampling.sampled_cosines(m, 5.0, 2), "i", "j").items()}
    assert one == two and one != other


@pytest.mark.parametrize("method", ["pair", "staged", "thinned"])
def test_unbiased_with_bounded_variance(spark, method):
    m = workloads.matrix(spark, SMALL, "w4")
    norms, seeds, gamma = column_norms(m).persist(), list(range(24)), 8.0
    exact = gram.exact_cosines(m, norms)
    cells = accuracy.grid(sampling.repeated_estimates(m, method, gamma, seeds, norms), exact, seeds)
    moments = accuracy.entry_moments(cells).collect()
    bias = np.mean([r["bias"] for r in moments])
    spread = math.sqrt(np.mean([r["variance"] for r in moments]) / (len(seeds) * len(moments)))
    assert abs(bias) < 5 * spread
    if method == "pair":
        assert np.mean([r["variance"] for r in moments]) <= planner.key_bound(1 / gamma) * 1.2


def test_pairs_never_kept_count_as_zero(spark):
    exact = spark.createDataFrame([(0, 1, 0.5)], "i int, j int, cos double")
    none = spark.createDataFrame([], "seed int, i int, j int, cos double")
    rates = accuracy.tail_rates(accuracy.grid(none, exact, [1, 2]), 0.5).first()
    assert rates["cells"] == 2 and rates["under"] == 1.0


def test_fourth_moment_needs_the_paired_indices(spark):
    """Two equal 0/1 columns of m ones: the kept count is binomial, its fourth moment near 3/gamma^2."""
    g, m = 100.0, 10_000
    p = g / m
    fourth = (m * p * (1 - p) * (1 + 3 * (m - 2) * p * (1 - p))) / g**4
    assert 2 / g**2 < fourth <= accuracy.moment_bounds(g)[1]


def test_emissions_are_near_their_expectation(spark):
    m = workloads.matrix(spark, SMALL, "w4b")
    norms = column_norms(m).persist()
    expected = cost.expected_emissions(m, 2.0, norms).first()["expected"]
    p = matrix.profile(m).first()
    for method in ("pair", "staged", "thinned"):
        n = cost.emissions(m, method, 2.0, 5, norms).first()["emissions"]
        assert n <= expected + 6 * math.sqrt(expected) + 10
    assert expected <= planner.shuffle_bound(p["n"], p["row_max"], 2.0, p["h"])
    half = cost.expected_emissions(m, 2.0, norms, row_share=0.5).first()["expected"]
    assert abs(half - expected) < 0.25 * expected


def test_draw_counts(spark):
    m = workloads.matrix(spark, SMALL, "w4")
    n = {k: cost.draw_count(m, k, 2.0).first()["draws"] for k in ("pair", "staged", "thinned")}
    assert n["thinned"] < n["staged"]
    assert n["pair"] == cost.naive_cost(m).first()["emissions"]


def test_block_construction(spark):
    m = workloads.block_matrix(spark, 60, 6)
    found = sampling.sampled_cosines(m, 6.0).collect()
    assert len(found) == planner.lower_bound(60, 6) == 150 and all(abs(r["cos"] - 1) < 1e-12 for r in found)


def test_scaling_keeps_relative_errors(spark):
    """Scaled by t with gamma by t^2 the same products are kept."""
    m = workloads.matrix(spark, SMALL, "w4c")
    most = matrix.max_abs(m)
    a = table(sampling.sampled_cosines(m, 2.0 * most**2, 3), "i", "j")
    b = table(sampling.sampled_cosines(matrix.scale_entries(m), 2.0, 3), "i", "j")
    assert a.keys() == b.keys() and all(abs(a[k]["cos"] - b[k]["cos"]) < 1e-9 for k in a)


def test_similar_columns_and_recall(spark):
    m = workloads.matrix(spark, "/root/testdata/sf0.01", "w2b")
    found = similarity.similar_columns(m, 0.5, verify=True)
    report = similarity.pair_recall(found, gram.exact_cosines(m), 0.5).first()
    assert report["precision"] == 1.0 and report["recall"] >= 0.98


def test_entry_estimates_cover_every_wanted_pair(spark, tiny):
    wanted = spark.createDataFrame([(1, 0), (0, 2), (0, 2)], "i int, j int")
    rows = table(similarity.entry_estimates(tiny, wanted, 1.0, 7, draw="md5"), "i", "j")
    assert rows[0, 1]["cos"] == pytest.approx(1.0) and rows[0, 2]["cos"] == 0.0 and len(rows) == 2


def test_norm_compatible_pairs(spark):
    norms = spark.createDataFrame([(c, 1, float(v * v), float(v)) for c, v in enumerate([1, 2, 3, 4, 4.4, 9])], "col int, nnz long, sumsq double, norm double")
    want = {(i, j) for i, a in enumerate([1, 2, 3, 4, 4.4, 9]) for j, b in enumerate([1, 2, 3, 4, 4.4, 9]) if i < j and min(a, b) >= 0.7 * max(a, b)}
    assert {(r["i"], r["j"]) for r in similarity.norm_compatible_pairs(norms, 0.7).collect()} == want


def test_planner():
    assert planner.gamma_for_spectral(100, 0.1, 0.7) == pytest.approx(4 * 0.49 * 100 / 0.01)
    a = planner.alpha_for(0.5, 0.1, 1000)
    assert planner.over_tail(a, 0.5) + planner.under_tail(a, 0.5) <= 0.1 / 1000 * (1 + 1e-9)
    assert planner.over_tail(math.log(100), 0.5) == pytest.approx(0.61, abs=0.01) and planner.under_tail(math.log(100), 0.5) == pytest.approx(0.56, abs=0.01)
    profile = {"n": 100, "row_max": 13, "h": 1.0, "pairs": 10**12, "smallest": 1.0, "most": 1.0}
    assert planner.plan(profile, "spectral", eps=0.5).method == "pair"
    assert planner.plan(profile, "similar", s=0.3).method == "pair"
    one = planner.plan(profile, "similar", s=0.3)
    assert planner.plan(profile | {"most": 10.0}, "similar", s=0.3, method="pair").gamma == pytest.approx(100 * one.gamma)
    assert planner.plan(profile, "similar", s=0.3, method="thinned").gamma == pytest.approx(one.gamma / 0.3)
    assert "0.608" in planner.plan(profile | {"n": 100}, "similar", s=0.3, method="pair", alpha="log_n").guarantee
    assert planner.plan(profile | {"pairs": 10}, "similar", s=0.3).method == "exact"
    with pytest.raises(ValueError):
        planner.plan(profile, "spectral", eps=0.5, method="staged")
    assert planner.plan(profile, "spectral", eps=0.5, method="staged", allow_heuristic=True).guarantee.startswith("none")
    with pytest.raises(ValueError):
        planner.plan(profile | {"smallest": -1.0}, "similar", s=0.3)


def test_least_squares(spark):
    m = workloads.regression(spark, SMALL)
    x = np.array([r["coefficient"] for r in least_squares.normal_equations(m, 4).orderBy("col").collect()])
    rows = spark.read.parquet(f"{SMALL}/lineitem.parquet").select("l_quantity", "l_discount", "l_tax", "l_extendedprice").toPandas().to_numpy()
    a = np.column_stack([rows[:, :3], np.ones(len(rows))])
    assert np.allclose(x, np.linalg.lstsq(a, rows[:, 3], rcond=None)[0], rtol=1e-6)


def test_weyl_and_norms():
    rng = np.random.default_rng(1)
    a = rng.normal(size=(30, 6))
    g = a.T @ a
    h = g + 0.1 * np.eye(6)
    s, t = spectral.decompose(g)[0], spectral.decompose(h)[0]
    assert accuracy.sigma_errors(s, t).max() <= spectral.spectral_norm(g - h) + 1e-9
    assert np.allclose(s, np.linalg.svd(a)[1])
    assert spectral.spectral_error(h, g) == pytest.approx(0.1 / s[0] ** 2)
    assert accuracy.success_rate([0.1, 0.2, 0.3], 0.2) == pytest.approx(2 / 3)


def test_negative_eigenvalues_count_as_zero():
    sigma, _ = spectral.decompose(np.array([[1.0, 2.0], [2.0, 1.0]]))
    assert sigma[1] == 0.0 and sigma[0] == pytest.approx(math.sqrt(3))


def exchanges(df) -> list[str]:
    plan = df._jdf.queryExecution().executedPlan().toString()
    return [line for line in plan.splitlines() if "Exchange hashpartitioning" in line]


def test_plan_has_one_exchange_on_pairs(spark, tmp_path):
    """From stored row form the only shuffle is of the sums, by pair."""
    from tallgram.sources.files import load_rows, save_rows

    save_rows(workloads.matrix(spark, SMALL, "w4"), str(tmp_path / "rows"))
    m = load_rows(spark, str(tmp_path / "rows"))
    norms = column_norms(m)
    for method in ("pair", "staged", "thinned"):
        found = exchanges(sampling.estimate(m, method, 5.0, norms=norms))
        assert len(found) == 1 and "row_id" not in found[0] and "i#" in found[0]


# --- forms and edges ---


def test_row_form_sums_duplicates_and_drops_zeros(spark):
    t = spark.createDataFrame([(1, 0, 2.0), (1, 0, 3.0), (1, 1, -0.0), (2, 1, 1.0), (2, 2, 1.5), (2, 2, -1.5), (3, 0, None), (3, 1, float("nan")), (3, 2, float("inf"))], "row_id long, col int, val double")
    rows = {r["row_id"]: [tuple(e) for e in r["entries"]] for r in matrix.to_row_form(matrix.drop_invalid(t)).collect()}
    assert rows == {1: [(0, 5.0)], 2: [(1, 1.0)]}
    with pytest.raises(Exception, match="null, NaN or infinite"):
        matrix.drop_invalid(t, "raise").collect()


def test_empty_matrix(spark):
    m = make(spark, [])
    assert matrix.max_abs(m) == 0.0 and matrix.profile(m).first()["m"] == 0
    for df in (gram.exact_gram(m), gram.exact_cosines(m), *(sampling.estimate(m, k, 1.0) for k in ("pair", "staged", "thinned"))):
        assert df.count() == 0
    assert spectral.decompose(np.zeros((0, 0)))[0].size == 0


def test_single_columns_signs_and_dense_rows(spark):
    assert gram.exact_cosines(make(spark, [(0, [(0, 1)]), (1, [(0, 2)])])).count() == 0
    m = make(spark, [(0, [(0, 1), (1, 1)]), (1, [(0, 1), (1, -1)])])
    assert gram.exact_cosines(m).first()["cos"] == 0.0
    zero = make(spark, [(0, [(0, 1), (2, 1)])])
    assert [tuple(r)[:2] for r in gram.exact_gram(zero).collect()] == [(0, 2)]


def test_bad_arguments(tiny):
    for call in (lambda: sampling.sampled_cosines(tiny, 0.0), lambda: sampling.uniform_cosines(tiny, 0.0), lambda: sampling.staged_cosines(tiny, 1.0, order="none"), lambda: sampling.estimate(tiny, "best", 1.0), lambda: planner.gamma_for_similarity(2.0, 1.0)):
        with pytest.raises(ValueError):
            call()


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet", "text"])
def test_triplet_files(spark, tmp_path, fmt):
    from tallgram.sources.files import load_triplets, save_triplets

    t = workloads.triplets(spark, SMALL, "w4")
    save_triplets(t, str(tmp_path / fmt), fmt)
    assert sorted(map(tuple, load_triplets(spark, str(tmp_path / fmt), fmt).collect())) == sorted(map(tuple, t.collect()))


def test_pair_files_and_buckets(spark, tmp_path):
    from tallgram.sources.files import load_pairs, save_bucketed, save_pairs
    from tallgram.sources.tables import load_table, with_row_ids

    g = gram.exact_gram(workloads.matrix(spark, SMALL, "w4"))
    save_pairs(g, str(tmp_path / "pairs"), block=5)
    assert load_pairs(spark, str(tmp_path / "pairs"), 6, 12, 5).count() == g.where("i between 6 and 12").count()
    save_bucketed(workloads.triplets(spark, SMALL, "w4"), "bucketed_w4", 4)
    joined = gram.exact_gram_join(spark.table("bucketed_w4"))
    assert not [x for x in exchanges(joined) if "row_id" in x]
    assert joined.count() == g.count()
    rows = with_row_ids(load_table(spark, SMALL, "nation"))
    assert rows.select("file", "row").distinct().count() == rows.count()


def test_power_iteration(spark, tiny):
    upper = gram.gram_from_cosines(gram.exact_cosines(tiny), column_norms(tiny))
    value, _ = spectral.top_by_power_iteration(gram.mirror(upper), rounds=40)
    assert value == pytest.approx(6.119027, abs=1e-5)


def test_stream_late_rows_are_dropped(spark, tmp_path):
    """A file that comes after the watermark has passed its time adds nothing in append mode."""
    import datetime

    from tallgram.streaming import events as E

    def file(name, hours):
        rows = [(i, datetime.datetime(2024, 1, 1) + datetime.timedelta(hours=h), 1, "view", 1.0, "{}") for i, h in enumerate(hours)]
        spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.parquet(str(tmp_path / "in" / name))

    file("a", [1, 2])
    stream = E.emissions_per_day(E.watermarked(E.stream_events(spark, str(tmp_path / "in" / "*"), 1)))
    q = stream.writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", str(tmp_path / "c")).start()
    q.processAllAvailable()
    file("b", [60])
    q.processAllAvailable()
    file("c", [3])
    q.processAllAvailable()
    file("d", [120])
    q.processAllAvailable()
    q.stop()
    assert {str(r["day"])[:10]: r["n"] for r in spark.table("late").collect()}["2024-01-01"] == 2


def test_promises_hold_on_unscaled_entries(spark):
    """Pairs over s are within 1 +- delta, all at once, under nearly every seed: pair method and raised thinned budget."""
    m = workloads.matrix(spark, SMALL, "w4c")
    norms, seeds, s = column_norms(m), list(range(10)), 0.1
    exact = gram.exact_cosines(m, norms)
    profile = matrix.profile(m).first().asDict()
    assert profile["most"] > 10
    for method in ("pair", "staged", "thinned"):
        p = planner.plan(profile, "similar", s=s, method=method, fail=0.1)
        cells = accuracy.grid(sampling.repeated_estimates(m, method, p.gamma, seeds, norms), exact, seeds).where(F.col("exact") >= s)
        off = cells.where(F.abs(F.col("cos") - F.col("exact")) > 0.5 * F.col("exact")).select("seed").distinct().count()
        assert cells.count() > 0 and off <= 3


def test_effective_budget_of_pairs_that_qualify(spark):
    m = workloads.matrix(spark, SMALL, "w2b")
    norms = {r["col"]: r["norm"] for r in column_norms(m).collect()}
    s, alpha = 0.3, 20.0
    gamma = planner.gamma_for_similarity(s, alpha, "thinned", 1.0)
    for r in gram.exact_cosines(m).where(F.col("cos") >= s).collect():
        a, b = norms[r["i"]], norms[r["j"]]
        acts = planner.effective_gamma(gamma, a, b, "thinned")
        assert acts >= alpha / s * (1 - 1e-9) or acts >= a * b * (1 - 1e-9)  # enough, or every product is kept


def test_negative_entries_are_refused(spark):
    m = make(spark, [(0, [(0, 1.0), (1, -1.0)]), (1, [(0, 1.0), (1, 1.0)])])
    with pytest.raises(ValueError):
        similarity.similar_columns(m, 0.3)


def test_norms_are_computed_once(spark):
    """The first query over some norms runs the action that fetches them; building further ones starts no job."""
    m = workloads.matrix(spark, SMALL, "w4")
    tracker, group = spark.sparkContext.statusTracker(), "norms-once"
    spark.sparkContext.setJobGroup(group, group)
    try:
        norms = column_norms(m)
        sampling.estimate(m, "pair", 5.0, 1, norms)
        first = len(tracker.getJobIdsForGroup(group))  # stages that AQE runs on their own count as jobs
        for method in ("pair", "staged", "thinned"):
            sampling.estimate(m, method, 5.0, 2, norms)
        gram.exact_cosines(m, norms)
        sampling.repeated_estimates(m, "pair", 5.0, [1, 2, 3], norms)
        assert first >= 1 and len(tracker.getJobIdsForGroup(group)) == first
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


def test_seeds_are_read_in_one_scan(spark, tmp_path):
    path = str(tmp_path / "rows")
    workloads.matrix(spark, SMALL, "w4").write.parquet(path)
    m = spark.read.parquet(path)
    norms = spark.createDataFrame(column_norms(m).toArrow())
    several = sampling.repeated_estimates(m, "pair", 5.0, [1, 2, 3], norms)
    assert several._jdf.queryExecution().executedPlan().toString().count("FileScan") == 1
    for seed in (1, 2, 3):
        one = table(sampling.estimate(m, "pair", 5.0, seed, norms), "i", "j")
        got = table(several.where(F.col("seed") == seed), "i", "j")
        assert one.keys() == got.keys() and all(abs(one[k]["cos"] - got[k]["cos"]) < 1e-9 for k in one)


def test_heavy_rows_in_pieces_give_the_same(spark):
    m = workloads.matrix(spark, SMALL, "w2b")
    norms, pieces = column_norms(m), matrix.split_heavy(m, 5)
    assert pieces.count() > m.count()
    assert {tuple(r) for r in gram.exact_gram(pieces).collect()} == {tuple(r) for r in gram.exact_gram(m).collect()}
    for method in ("pair", "staged"):
        a, b = (table(sampling.estimate(x, method, 4.0, 3, norms), "i", "j") for x in (m, pieces))
        assert a.keys() == b.keys() and all(abs(a[k]["cos"] - b[k]["cos"]) < 1e-9 for k in a)


def test_library_second_opinion(spark):
    """The public library's own similarity and factorisation agree on a workload."""
    from pyspark.mllib.linalg import Vectors
    from pyspark.mllib.linalg.distributed import RowMatrix

    m = workloads.matrix(spark, SMALL, "w4")
    n = 25
    other = RowMatrix(m.rdd.map(lambda r: Vectors.sparse(n, [(e["col"], e["val"]) for e in r["entries"]])))
    cosines = {(int(e.i), int(e.j)): e.value for e in other.columnSimilarities().entries.collect()}
    mine = table(gram.exact_cosines(m), "i", "j")
    assert cosines.keys() == mine.keys() and all(abs(cosines[k] - mine[k]["cos"]) < 1e-9 for k in mine)
    norms = column_norms(m)
    upper = gram.gram_from_cosines(gram.exact_cosines(m, norms), norms)
    sigma = [r["sigma"] for r in spectral.spectral_factors(upper, n)[0].orderBy("rank").collect()]
    assert np.allclose(other.computeSVD(n).s.toArray(), sigma[: len(other.computeSVD(n).s.toArray())], rtol=1e-6)
    a = np.zeros((m.count(), n))
    for k, r in enumerate(m.collect()):
        for e in r["entries"]:
            a[k, e["col"]] = e["val"]
    assert np.allclose(np.linalg.svd(a, compute_uv=False), sigma, rtol=1e-6)


def test_cosine_error_and_bytes(spark):
    m = workloads.matrix(spark, SMALL, "w4")
    norms = column_norms(m)
    exact = spectral.dense(gram.exact_cosines(m, norms), 25, "cos")
    few, many = (accuracy.cosine_error(spectral.dense(sampling.sampled_cosines(m, g, 1, norms), 25, "cos"), exact) for g in (2.0, 200.0))
    assert many < few
    records, size = cost.shuffled(sampling.sampled_cosines(m, 2.0, 1, norms))
    whole, whole_size = cost.shuffled(gram.exact_gram(m, combine=False))
    assert 0 < records < whole and 0 < size < whole_size and whole == cost.emissions(m, "exact").first()["emissions"]
