import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from meshprofile.operators import consensus as C
from meshprofile.operators import masking, metrics, privacy, secure
from meshprofile.sources import graphs as G

SECRETS = masking.fixed_secrets(10)
X = np.random.default_rng(0).normal(5, 2, (10, 4))


def run(kind, rounds=60, **how):
    return C.run_numpy(X, C.Setting(G.main_graph(), 10, kind, stop="fixed", rounds=rounds, secrets=SECRETS, **how))


@pytest.mark.parametrize("kind", C.KINDS)
def test_every_kind_reaches_the_mean(kind):
    assert np.abs(run(kind, 90) - X.mean(0)).max() < 1e-9


@pytest.mark.parametrize("kind", C.KINDS)
@pytest.mark.parametrize("engine", ["array", "block", "edge", "closed", "driver"])
def test_engines_agree(spark, kind, engine):
    s = C.Setting(G.main_graph(), 10, kind, stop="fixed", rounds=7, scale=np.array([1.0, 2.0, 5.0, 0.5]))
    got, _ = C.dense(C.run(C._to_state(spark, X, [0, 1, 2, 3]), s, engine, nonce="n"), 10)
    assert np.abs(got - C.run_numpy(X, s, "n")).max() < 1e-9


@pytest.mark.parametrize("engine", ["array", "block", "edge", "driver", "closed"])
def test_two_term_form_equals_the_matrix(spark, engine):
    how = {"stop": "fixed", "rounds": 5, "secrets": SECRETS}
    one, two = C.Setting(G.main_graph(), 10, **how), C.Setting(G.main_graph(), 10, form="two_term", **how)
    assert np.abs(C.run_numpy(X, one) - C.run_numpy(X, two)).max() < 1e-12
    state = C._to_state(spark, X, [0, 1, 2, 3])
    if engine == "closed":
        with pytest.raises(ValueError):
            C.run(state, two, engine)
    else:
        assert np.abs(C.dense(C.run(state, two, engine, nonce="0"), 10)[0] - C.run_numpy(X, one)).max() < 1e-9


def test_masks_shrink_telescope_and_vanish():
    s = C.Setting(G.main_graph(), 10, secrets=SECRETS)
    for t in range(6):
        assert np.abs(masking.delta_array(SECRETS, "0", [0, 1], t, 2.0, 0.2)).max() <= 0.2 ** (t + 1)
    added = sum(s.theta("0", [0, 1, 2, 3], t) for t in range(5))
    assert np.allclose(added, masking.delta_array(SECRETS, "0", [0, 1, 2, 3], 4, 2.0, 0.2))
    x = run("masked_boosted", 5)
    assert np.allclose(x.sum(0) - X.sum(0), added.sum(0), atol=1e-10)
    assert np.array_equal(run("masked_boosted", 5, beta=0.0), run("boosted", 5))


def test_no_two_exchanges_share_a_draw_and_no_party_knows_anothers():
    s, again = C.Setting(G.main_graph(), 10, secrets=SECRETS), C.Setting(G.main_graph(), 10, secrets=SECRETS)
    names = [s.nonce() for _ in range(20)] + [again.nonce() for _ in range(20)]
    draws = np.concatenate([s.delta(n, list(range(24)), 0).ravel() for n in names])
    assert len(np.unique(draws)) == len(draws)
    assert privacy.shared_draws(s, 30) == 0
    assert all(privacy.guessed_masks(s, p) == 0 for p in range(10))
    fresh = C.Setting(G.main_graph(), 10)
    assert len(set(fresh.secrets)) == 10 and not set(fresh.secrets) & set(C.Setting(G.main_graph(), 10).secrets)
    with pytest.raises(ValueError):
        C.Setting(G.main_graph(), 10, secrets=("s",) * 10)


def test_fits_on_one_setting_never_repeat_draws(spark, monkeypatch):
    from meshprofile.operators import cluster as K

    seen, real = [], masking.delta_array
    monkeypatch.setattr(masking, "delta_array", lambda secrets, nonce, comps, t, *a: seen.append((nonce, t)) or real(secrets, nonce, comps, t, *a))
    rows = spark.createDataFrame([(i % 10, i, [float(i), 1.0]) for i in range(30)], "party int, id long, y array<double>")
    s = C.Setting(G.main_graph(), 10)
    mu = K.masked_start(rows, 2, s)
    for _ in range(2):
        K.fit_kmeans(rows, mu, s, iterations=2, stop="fixed")
    first = [n for n, t in seen if t == 0]
    assert len(set(first)) == 5 == s.exchanges


def test_a_lookup_serves_only_its_own_components():
    s = C.Setting(G.main_graph(), 10, secrets=SECRETS)
    s.prepare("0", [0, 1, 2])
    assert np.array_equal(s.delta("0", [5, 6, 7], 0), masking.delta_array(SECRETS, "0", [5, 6, 7], 0, s.sigma, s.beta))
    assert not np.array_equal(s.delta("0", [5, 6, 7], 0), s.delta("0", [0, 1, 2], 0))


def test_boosted_needs_fewer_rounds_and_masks_cost_little():
    def rounds(kind):
        log = []
        C.run_numpy(X, C.Setting(G.main_graph(), 10, kind, stop="fixed", rounds=80, secrets=SECRETS), trace=log)
        return next(t for t, _, x in log if (np.linalg.norm(10 * x - X.sum(0), axis=1) / np.linalg.norm(X.sum(0))).mean() < 1e-6)

    got = {k: rounds(k) for k in C.KINDS}
    assert got["boosted"] < got["plain"] and got["masked_boosted"] < got["masked_plain"]
    assert abs(got["masked_boosted"] - got["boosted"]) <= 2


def test_stops(spark):
    s = C.Setting(G.main_graph(), 10)
    assert s.rounds == 31 and s.rho < 0.64
    state = C._to_state(spark, X, [0, 1, 2, 3])
    for stop in ("spread", "max_consensus"):
        one = C.Setting(G.main_graph(), 10, stop=stop)
        x, t = C.run_counted(X, one)
        assert np.abs(x - X.mean(0)).max() < 1e-4 and 0 < t < 60 and (stop == "spread" or t % 3 == 0)
        for engine in ("block", "driver"):
            assert np.abs(C.dense(C.run(state, one, engine), 10)[0] - X.mean(0)).max() < 1e-4
        for engine in ("array", "edge", "closed"):
            with pytest.raises(ValueError):
                C.run(state, one, engine)
        with pytest.raises(ValueError):
            C.run_numpy(X, C.Setting(G.main_graph(), 10, stop=stop, rounds=3))


@pytest.mark.parametrize("how", [{"stop": "fixed"}, {"stop": "spektral"}, {"stop": ""}, {"form": "x"}, {"exposed": "x"}, {"kind": "x"}])
def test_no_setting_gives_totals_of_no_rounds(how):
    with pytest.raises(ValueError):
        C.Setting(G.main_graph(), 10, **how)


@pytest.mark.parametrize("stop", C.STOPS)
def test_every_stop_mixes(stop):
    s = C.Setting(G.ring(5), 5, stop=stop, rounds=80 if stop == "fixed" else 0)
    x, t = C.run_counted(X[:5], s)
    assert t > 0 and np.abs(x - X[:5].mean(0)).max() < 1e-3


def test_exposed_edges_are_dropped_by_default():
    from meshprofile.operators import topology as T

    pruned = 0
    for seed in range(300):
        pairs = G.random_connected(8, 16, seed)
        if not T.exposed_pairs(pairs):
            continue
        with pytest.raises(ValueError):
            C.Setting(pairs, 8, exposed="raise")
        try:
            left = C.Setting(pairs, 8).pairs
        except ValueError:
            continue  # dropping them would cut a party off
        assert set(left) < set(pairs) and not T.exposed_pairs(left) and T.is_connected(left, 8)
        pruned += 1
    assert pruned
    with pytest.raises(ValueError):
        C.Setting(G.named("unsafe"), 10)
    with pytest.raises(ValueError):
        C.Setting(G.complete(4), 4)  # without the exposed edges nothing is left
    assert C.Setting(G.named("unsafe"), 10, "boosted").pairs == G.named("unsafe")
    with pytest.warns(UserWarning):
        C.Setting([(0, 1)], 2)


def test_odd_states(spark):
    s = C.Setting(G.main_graph(), 10, stop="fixed", rounds=90)
    rows = [(0, 0, 1.0), (0, 0, 2.0), (1, 0, None), (None, 0, 5.0), (2, None, 5.0), (3, 0, 4.0)]
    state = spark.createDataFrame(rows, "party int, comp int, x double")
    for engine in ("array", "block", "edge", "driver"):
        assert np.abs(C.dense(C.totals(state, s, engine).withColumnRenamed("total", "x"), 10)[0] - 7).max() < 1e-8
    assert C.totals(state.limit(0), s, "block").count() == 0
    with pytest.raises(ValueError):
        C.totals(spark.createDataFrame([(12, 0, 1.0)], "party int, comp int, x double"), s, "driver").count()
    with pytest.raises(ValueError):
        C.run(state, C.Setting(G.ring(300), 300, stop="fixed", rounds=200), "closed")


def test_disconnected_and_single(spark):
    with pytest.raises(ValueError):
        C.Setting(G.named("split"), 10)
    one = C.Setting([], 1)
    assert one.rounds == 0 and np.array_equal(C.run_numpy(X[:1], one), X[:1])


def test_a_party_without_rows_takes_part(spark):
    s = C.Setting(G.main_graph(), 10, stop="fixed", rounds=90)
    state = C._to_state(spark, X[:4], [0, 1, 2, 3])
    for engine in ("array", "block", "edge", "closed"):
        got, _ = C.dense(C.run(state, s, engine), 10)
        assert np.abs(10 * got - X[:4].sum(0)).max() < 1e-8


def test_mask_table_equals_recomputed_masks(spark):
    state, draws = C._to_state(spark, X, [0, 1, 2, 3]), masking.mask_table(spark, SECRETS, "0", 4, 3)
    a = {(r.party, r.comp): r.shared for r in masking.mask_from_table(state, draws, 1).collect()}
    want = X + C.Setting(G.main_graph(), 10, secrets=SECRETS).theta("0", [0, 1, 2, 3], 1)
    for secrets in (masking.secrets_table(spark, SECRETS), masking.secret_of(SECRETS)):
        b = {(r.party, r.comp): r.shared for r in masking.mask(state, 1, secrets).collect()}
        assert len(b) == 40 and all(abs(a[k] - v) < 1e-12 and abs(want[k] - v) < 1e-12 for k, v in b.items())


def test_secret_shares(spark):
    x = np.round(X - 5, 6)
    got = {r.comp: r.total for r in secure.additive_shares(C._to_state(spark, x, [0, 1, 2, 3]), 10).collect()}
    assert all(abs(got[i] - x[:, i].sum()) < 1e-9 for i in range(4))


def test_audits():
    s, counts = C.Setting(G.main_graph(), 10), np.arange(60.0).reshape(10, 6)
    assert privacy.count_rounding_attack(counts, s) == 1.0 and privacy.count_rounding_attack(counts, s, 100) < 0.2
    assert privacy.count_rounding_attack(counts, C.Setting(G.main_graph(), 10, scale=100.0)) < 0.2
    bad = C.Setting(G.named("unsafe"), 10, exposed="allow")
    assert np.abs(privacy.rebuild(X, bad, 0, 1) - X[1]).max() < 1e-12
    assert np.abs(privacy.rebuild(X, s, 0, 5) - X[5]).max() > 0.5


def test_error_measure(spark):
    state = C._to_state(spark, X, [0, 1, 2, 3])
    from pyspark.sql import functions as F

    trace = C.run(state, C.Setting(G.main_graph(), 10, stop="fixed", rounds=40), "block", trace=True).withColumn("kind", F.lit("m"))
    err = metrics.consensus_error(trace, C.direct_sum(state), 10)
    assert metrics.rounds_to(err).first().rounds in range(25, 36)


@settings(max_examples=25, deadline=None)
@given(st.integers(4, 9), st.integers(0, 6), st.integers(0, 99))
def test_sums_are_kept_on_random_graphs(n, extra, seed):
    pairs = G.random_connected(n, min(n - 1 + extra, n * (n - 1) // 2), seed)
    x = np.random.default_rng(seed).normal(size=(n, 2))
    s = C.Setting(pairs, n, "boosted", stop="fixed", rounds=3)
    assert np.allclose(C.run_numpy(x, s).sum(0), x.sum(0))


def test_mixing_by_join_needs_no_matrix(spark):
    from meshprofile.operators import topology as T

    weights = T.boost(T.mixing(G.edges_df(spark, G.main_graph())), 0.2965)
    got, _ = C.dense(C.mix_by_join(C._to_state(spark, X, [0, 1, 2, 3]), weights, 6), 10)
    want = C.run_numpy(X, C.Setting(G.main_graph(), 10, "boosted", a=0.2965, stop="fixed", rounds=6))
    assert np.abs(got - want).max() < 1e-9
    with pytest.raises(ValueError):
        C.mix_by_join(C._to_state(spark, X, [0, 1, 2, 3]), weights, 6, sigma=1.0)
