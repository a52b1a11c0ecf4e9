import numpy as np
import pytest

from meshprofile.operators import cluster as K
from meshprofile.operators import consensus as C
from meshprofile.operators import cost, metrics
from meshprofile.operators.families import FuzzyCMeans, GaussianMixture, KMeans, Model
from meshprofile.sources import tables
from meshprofile.plans import methods as Q
from meshprofile.sources import graphs as G

Y = np.random.default_rng(1).normal(size=(60, 5)) + np.repeat([[0], [4], [9]], 20, 0)
MU = Y[[0, 25, 50]] + 0.3


@pytest.fixture(scope="module")
def profiles(spark):
    return spark.createDataFrame([(i % 10, i, y.tolist()) for i, y in enumerate(Y)], "party int, id long, y array<double>")


@pytest.mark.parametrize("fit, how", [(K.fit_kmeans, {}), (K.fit_fuzzy, {}), (K.fit_fuzzy, {"weighting": "as_printed", "m": 1.5}), (K.fit_gmm, {"cov": "full", "reg": 1e-3}), (K.fit_gmm, {"cov": "diag"}), (K.fit_gmm, {"cov": "spherical"})])
def test_masked_equals_central(profiles, fit, how):
    s = C.Setting(G.main_graph(), 10, eps=1e-9)
    a, ra = fit(profiles, MU, iterations=4, **how)
    b, rb = fit(profiles, MU, s, iterations=4, **how)
    assert a.gap(b) < 1e-6 and ra.iterations == rb.iterations and rb.disagreement < 1e-3
    up = np.diff(ra.objective)
    if fit is K.fit_gmm:
        assert (up > -1e-6 * abs(ra.objective[0])).all()
    elif how.get("weighting") != "as_printed":
        assert (up < 1e-9).all()


def test_one_exchange_equals_two(profiles):
    s, family = C.Setting(G.main_graph(), 10, eps=1e-10), GaussianMixture("full", reg=1e-3)
    start = family.start(MU)
    one, _ = K.fit(profiles, family, start, s, iterations=1, stop="fixed")
    two = K.fit_two_round(profiles, family, start, s, 1)
    inexact, _ = K.fit(profiles, GaussianMixture("full", "old_mean", 1e-3), start, s, iterations=1, stop="fixed")
    assert np.abs(one.sigma - two.sigma).max() < 1e-6 < np.abs(inexact.sigma - two.sigma).max()


def test_shares_sum_to_one_and_crisp_rows():
    on = np.vstack([MU[1], Y[:3]])
    for family, m in ((FuzzyCMeans(), Model(MU)), (FuzzyCMeans(1.2), Model(MU)), (GaussianMixture("diag"), GaussianMixture("diag").start(MU))):
        assert np.allclose(family.share(on, m).sum(1), 1)
    assert np.array_equal(FuzzyCMeans().share(on, Model(MU))[0], [0, 1, 0])


def test_edges_of_kmeans(profiles):
    far = np.vstack([MU, np.full(5, 1e3)])
    keep, _ = K.fit_kmeans(profiles, far, iterations=2)
    assert np.array_equal(keep.mu[3], far[3])
    moved, _ = K.fit_kmeans(profiles, far, iterations=2, on_empty="reseed")
    assert np.abs(moved.mu[3]).max() < 100
    one, _ = K.fit_kmeans(profiles, MU[:1], iterations=2)
    assert np.allclose(one.mu[0], Y.mean(0))


def test_sql_assignment_equals_numpy(profiles):
    got = {r.id: r.k for r in K.assign_hard(profiles, MU).collect()}
    want = KMeans().share(Y, Model(MU)).argmax(1)
    assert all(got[i] == want[i] for i in range(60))
    soft = K.predict(profiles, FuzzyCMeans(), Model(MU), soft=True).orderBy("id").collect()
    assert np.allclose([r.u for r in soft], FuzzyCMeans().share(Y, Model(MU)))


def test_silhouette_against_all_pairs(profiles):
    a = K.assign_hard(profiles, MU)
    k = KMeans().share(Y, Model(MU)).argmax(1)
    for how, power in (("exact", 0.5), ("squared", 1.0)):
        d = (((Y[:, None] - Y) ** 2).sum(2)) ** power
        s = []
        for i in range(60):
            m = [d[i][(k == c) & (np.arange(60) != i)].mean() for c in range(3)]
            b = min(m[c] for c in range(3) if c != k[i])
            s.append((b - m[k[i]]) / max(b, m[k[i]]))
        assert abs(metrics.silhouette(a, how) - np.mean(s)) < 1e-9


def test_moments_under_masks(profiles):
    mean, sd, n = C.masked_moments(profiles, C.Setting(G.main_graph(), 10, eps=1e-10))
    assert n == 60 and np.allclose(mean, Y.mean(0)) and np.allclose(sd, Y.std(0), atol=1e-6)


def test_elbow_and_missed_patterns(spark, sf):
    got = {(r.scope, r.k): r for r in Q.q_sse_by_k(spark, sf).collect()}
    assert got["union", 1].chosen == 6 and got["party 0", 1].chosen == 2
    assert Q.q_missed_patterns(spark, sf).first().missed == 1000


def test_cost_figures():
    assert cost.payload("kmeans", 6, 48) == 294
    assert abs(cost.message_bytes(294) / 1024 - 1.15) < 0.005
    size = cost.upload_bytes(294, 5, 27, 7)
    assert abs(size / 1024 - 1086.75) < 1.1 * 5 and abs(size / 1024**2 - 1.06) < 0.01
    assert 0.7 < cost.link_seconds(size, 11.03) < 0.9
    assert cost.payload("gmm", 6, 48, triangle=False) == 14118 and cost.payload("gmm", 6, 48) == 7350


def test_select_rules():
    ks, v = [1, 2, 3, 4, 5], [100, 40, 12, 11, 10.5]
    assert K.knee(ks, v) == 3 and K.knee(ks, v, "second_diff") == 2 and K.knee(ks, v, "rel_drop", 0.2) == 3
    with pytest.raises(ValueError):
        K.knee(ks, v, "other")


def test_exact_silhouette_of_more_rows_than_a_driver_takes(spark):
    """No refusal: 20,480 rows in two far clusters."""
    df = spark.range(20_480).selectExpr("id", "int(id % 2) as k", "array(double(id % 2) * 1000, double(id % 7)) as y")
    assert 0.99 < metrics.silhouette(df, "exact") < 1


def silhouette_of(y, k, weight):
    """Mean Euclidean silhouette of points that occur `weight` times."""
    d, n = np.sqrt(((y[:, None] - y) ** 2).sum(2)), np.array([weight[k == c].sum() for c in range(k.max() + 1)])
    total = np.stack([(d * weight)[:, k == c].sum(1) for c in range(len(n))], 1)
    a, other = total[np.arange(len(y)), k] / np.maximum(n[k] - 1, 1), total / n
    other[np.arange(len(y)), k] = np.inf
    b = other.min(1)
    return np.average(np.where(n[k] > 1, (b - a) / np.maximum(a, b), 0), weights=weight)


def test_exact_silhouette_over_many_blocks_and_parts(spark, monkeypatch):
    for name, v in {"BLOCK": 40, "PART": 150, "HELD": 4000}.items():
        monkeypatch.setattr(metrics, name, v)
    rng = np.random.default_rng(3)
    y, k = rng.normal(0, 1, (701, 5)) + 1000, rng.choice(4, 701, p=[0.7, 0.2, 0.09, 0.01])
    k[0], y[1:200:2] = 4, y[0:199:2]  # a cluster of one row, equal rows
    df = spark.createDataFrame([(i, int(c), v.tolist()) for i, (c, v) in enumerate(zip(k, y))], "id long, k int, y array<double>").repartition(3)
    assert abs(metrics.silhouette(df, "exact") - silhouette_of(y, k, np.ones(701))) < 1e-7


def test_exact_silhouette_takes_forty_billion_distances_in_a_minute(spark):
    import time

    rng = np.random.default_rng(4)
    y, k = rng.normal(0, 1, (1000, 12)), np.arange(1000) % 6
    points = spark.createDataFrame([(int(c), v.tolist()) for c, v in zip(k, y)], "k int, y array<double>").coalesce(1)
    df = points.crossJoin(spark.range(200)).select("k", "y").repartition(8)
    began = time.perf_counter()
    assert abs(metrics.silhouette(df, "exact") - silhouette_of(y, k, np.full(1000, 200))) < 1e-6
    assert time.perf_counter() - began < 60


def test_planted_profiles_of_all_customers(spark, sf):
    n = spark.read.parquet(f"{sf}/customer.parquet").count()
    assert tables.planted(spark, sf, 12).count() == n > tables.planted(spark, sf, 12, 100).count() == 100
    assert tables.planted(spark, sf, 12, copies=3).select("id").distinct().count() == 3 * n


def test_many_fits_equal_single_ones(profiles):
    s = C.Setting(G.main_graph(), 10, eps=1e-10)
    mixture = GaussianMixture("diag", reg=1e-3)
    parts = [(KMeans(), Model(MU)), (FuzzyCMeans(), Model(MU[:2])), (mixture, mixture.start(MU))]
    for (family, start), (model, report) in zip(parts, K.fit_many(profiles, parts, s, iterations=4, stop="fixed")):
        one, alone = K.fit(profiles, family, start, None, iterations=4, stop="fixed")
        assert model.gap(one) < 1e-6 and report.iterations == alone.iterations == 4 and abs(report.objective[-1] / alone.objective[-1] - 1) < 1e-6


@pytest.mark.parametrize("stop", ["shift", "objective", "assignment"])
def test_stops_of_fits(profiles, stop):
    for s in (None, C.Setting(G.main_graph(), 10, eps=1e-9)):
        model, report = K.fit_kmeans(profiles, MU, s, stop=stop)
        assert report.converged and report.iterations < 50 and np.abs(np.sort(model.mu.mean(1)) - [0, 4, 9]).max() < 1
    with pytest.raises(ValueError):
        K.fit_kmeans(profiles, MU, stop="other")


@pytest.mark.parametrize("stop", ["spread", "max_consensus"])
def test_fits_with_stops_by_state(profiles, stop):
    a, _ = K.fit_kmeans(profiles, MU, iterations=3, stop="fixed")
    b, r = K.fit_kmeans(profiles, MU, C.Setting(G.main_graph(), 10, stop=stop, eps=1e-9), iterations=3, stop="fixed")
    assert a.gap(b) < 1e-4 and all(0 < t < 100 for t in r.rounds_per_iteration)


def test_payloads_beyond_the_driver(profiles, monkeypatch):
    s = C.Setting(G.main_graph(), 10, eps=1e-9)
    a, ra = K.fit_kmeans(profiles, MU, s, iterations=3, stop="fixed")
    monkeypatch.setattr(C, "DRIVER_CELLS", 20)
    b, rb = K.fit_kmeans(profiles, MU, s, iterations=3, stop="fixed")
    assert a.gap(b) < 1e-6 and rb.rounds_per_iteration == ra.rounds_per_iteration and len(rb.party_seconds) == 10
    with pytest.raises(ValueError):
        K.fit_kmeans(profiles, MU, s, iterations=1, stop="fixed", engine="driver")


def test_masks_of_a_fit_scaled_to_ranges(profiles):
    s = C.Setting(G.main_graph(), 10, eps=1e-12)
    a, _ = K.fit_kmeans(profiles, MU, iterations=3, stop="fixed")
    b, _ = K.fit_kmeans(profiles, MU, s, iterations=3, stop="fixed", ranges=(100, 15.0))
    assert a.gap(b) < 1e-6 and s.scale == 1.0
    widths = KMeans().ranges(Model(MU), 100, 15.0)
    assert len(widths) == KMeans().floats(Model(MU)) and widths[0] == 100 and widths[1] == 1500


def test_each_partys_own_model(profiles):
    models, _ = K.fit_kmeans(profiles, MU, C.Setting(G.main_graph(), 10, eps=1e-8), iterations=2, stop="fixed", per_party=True)
    assert len(models) == 10 and 0 < max(m.gap(models[0]) for m in models) < 1e-4


def test_odd_profiles(spark, profiles):
    kinds = "party int, id long, y array<double>"
    odd = profiles.unionByName(spark.createDataFrame([(1, 100, None), (None, 101, [1.0] * 5), (2, 102, [1.0, None, 1.0, 1.0, 1.0]), (3, 103, [float("nan")] * 5)], kinds))
    s = C.Setting(G.main_graph(), 10, eps=1e-10)
    for setting in (None, s):
        a, _ = K.fit_kmeans(profiles, MU, setting, iterations=2, stop="fixed")
        b, _ = K.fit_kmeans(odd, MU, setting, iterations=2, stop="fixed")
        assert a.gap(b) < 1e-6
        empty, report = K.fit_kmeans(profiles.limit(0), MU, setting, iterations=2)
        assert np.array_equal(empty.mu, MU) and report.iterations == 0
    assert {r.k for r in K.assign_hard(odd, MU).where("id = 100").collect()} == {None}
    soft = {r.id: r for r in K.assign_shares(odd.where("id in (0, 100)"), FuzzyCMeans(), Model(MU)).collect()}
    assert soft[100].u is None and soft[100].k is None and len(soft[0].u) == 3
    mean, sd, n = C.masked_moments(profiles.limit(0), s)
    assert len(mean) == len(sd) == n == 0
    with pytest.raises(ValueError):
        K.fit_kmeans(profiles.unionByName(spark.createDataFrame([(1, 100, [1.0])], kinds)), MU, iterations=1)
    with pytest.raises(ValueError):
        K.fit_kmeans(profiles.unionByName(spark.createDataFrame([(10, 100, [1.0] * 5)], kinds)), MU, s, iterations=1)
    few, _ = K.fit_kmeans(profiles.where("party < 3"), MU, s, iterations=2, stop="fixed")  # parties without rows take part
    alone, _ = K.fit_kmeans(profiles.where("party < 3"), MU, iterations=2, stop="fixed")
    assert few.gap(alone) < 1e-6


def test_fits_leave_nothing_in_the_shared_folder(profiles):
    from meshprofile import session

    before = len(session._written)
    for engine in ("driver", "block"):
        K.fit_kmeans(profiles, MU, C.Setting(G.main_graph(), 10), iterations=2, stop="fixed", engine=engine)
    assert len(session._written) == before


def test_silhouettes_of_many_models(profiles):
    models = [(KMeans(), Model(MU)), (FuzzyCMeans(), Model(MU[:2])), (KMeans(), Model(MU[:1]))]
    got = metrics.silhouettes(profiles, models)
    for (family, m), v in zip(models[:2], got):
        one = spark_labels(profiles, family.share(Y, m).argmax(1))
        assert abs(metrics.silhouette(one, "squared") - v) < 1e-9
    assert got[2] == 0


def spark_labels(profiles, k):
    rows = [(i, int(c), y.tolist()) for i, (c, y) in enumerate(zip(k, Y))]
    return profiles.sparkSession.createDataFrame(rows, "id long, k int, y array<double>")


@pytest.mark.parametrize("carrier", ["planted", "events"])
def test_silhouettes_agree_at_convergence_for_every_k(spark, sf, carrier):
    """Centralised and masked fits of each family end alike, K by K."""
    df = Q.carriers(spark, sf, 12)[carrier]
    parts = [(f, m) for k in (2, 4, 6, 8) for _, f, m in Q.three_families(K.public_peaks(k, 12)[0])]
    scores = []
    for s in (None, Q.setting(eps=1e-10)):
        got = K.fit_many(df, parts, s, iterations=25, tol=1e-3, settled=True)
        scores.append(metrics.silhouettes(df, [(f, m) for (f, _), (m, _) in zip(parts, got)]))
    assert np.allclose(*scores, atol=2e-3)
    if carrier == "planted":
        kmeans = scores[0][::3]
        assert int(np.argmax(kmeans)) == 2  # K = 6, as planted
