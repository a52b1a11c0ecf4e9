"""Queries of the methods, baselines, measures and workloads, with their SQL where SQL can say it."""

from __future__ import annotations

from functools import partial

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.functions.vectors import l2sq
from meshprofile.operators import cluster, consensus, cost, masking, metrics, privacy, profiles, secure, topology
from meshprofile.operators.families import FuzzyCMeans, GaussianMixture, KMeans, Model
from meshprofile.plans import duck
from meshprofile.sources import graphs, tables
from meshprofile.session import discard, settle
from meshprofile.sources.tables import table

K, T, SLOTS = 3, 3, 12
MU = cluster.public_random(K, SLOTS, "start", 0.8)
W_MAIN = topology.mixing_matrix(graphs.main_graph())
#: Secrets and an exchange name that the SQL side can recompute masks from; fits draw fresh ones.
SECRETS = masking.fixed_secrets(10)


def peak(spark: SparkSession, d: str, slots: int = SLOTS) -> DataFrame:
    """(party, id, y) peak-scaled profiles of users over ten parties."""
    built = profiles.standardise(profiles.build(tables.readings(spark, d), "user_id", "ts", "value", slots), "peak")
    return tables.parties_of_users(built).select("party", F.col("id").cast("long").alias("id"), "y")


def planted(spark: SparkSession, d: str, slots: int = SLOTS) -> DataFrame:
    """(party, id, y) planted profiles of every customer."""
    return tables.planted(spark, d, slots).select("party", "id", "y")


def setting(kind: str = "masked_boosted", **how) -> consensus.Setting:
    """The main graph under fresh secrets."""
    return consensus.Setting(graphs.main_graph(), 10, kind, **how)


def replayed(kind: str = "masked_boosted", **how) -> consensus.Setting:
    """The main graph under the fixed secrets; its first exchange is named 0."""
    return setting(kind, secrets=SECRETS, session="", **how)


def first_states(spark: SparkSession, d: str, slots: int = SLOTS) -> DataFrame:
    """Start states: the profile of each party's first consumer, slot by slot."""
    first = peak(spark, d, slots).groupBy("party").agg(F.min_by("y", "id").alias("y"))
    return first.select("party", F.posexplode("y").alias("comp", "x"))


def first_sql(slots: int) -> str:
    return duck.peak_profiles(slots) + ",\nstart as (select party, slot as comp, y as x from p where id in (select min(id) from p group by party))"


FIRST = first_sql(SLOTS)


# profiles ---------------------------------------------------------------------------------------------


def q_profile(how: str, slots: int, spark: SparkSession, d: str) -> DataFrame:
    built = profiles.build(tables.readings(spark, d), "user_id", "ts", "value", slots, how)
    return built.select(F.col("id").cast("long").alias("id"), F.posexplode("y").alias("slot", "v")).select("id", F.col("slot").cast("long").alias("slot"), F.round("v", 6).alias("v"))


def sql_profile(how: str, slots: int) -> str:
    if how == "sum":
        return f"with {duck.raw_slots(slots)} select id, slot::bigint as slot, round(v, 6) as v from grid"
    cell = {"mean": "avg(v)", "median": "median(v)", "trimmed_mean": "list_avg(list_slice(list_sort(list(v)), floor(count(*) * 0.1)::int + 1, count(*) - floor(count(*) * 0.1)::int))"}[how]
    return f"""with daily as (select user_id as id, ts::date as day, (hour(ts) * 60 + minute(ts)) // {1440 // slots} as slot, sum(value) as v from events group by all),
cells as (select id, slot, {cell} as v from daily group by all)
select u.id, r.s::bigint as slot, round(coalesce(c.v, 0), 6) as v from (select distinct user_id as id from events) u cross join range({slots}) r(s) left join cells c on c.id = u.id and c.slot = r.s"""


def q_standardise(how: str, spark: SparkSession, d: str) -> DataFrame:
    built = profiles.standardise(profiles.build(tables.readings(spark, d), "user_id", "ts", "value", SLOTS), how)
    return built.select(F.col("id").cast("long").alias("id"), F.posexplode("y").alias("slot", "v")).select("id", F.col("slot").cast("long").alias("slot"), F.round("v", 6).alias("v"))


STANDARDS = {
    "peak": "coalesce(v / nullif(max(v) over i, 0), 0)",
    "unit_sum": "coalesce(v / nullif(sum(v) over i, 0), 0)",
    "minmax": "coalesce((v - min(v) over i) / nullif(max(v) over i - min(v) over i, 0), 0)",
    "zscore_row": "coalesce((v - avg(v) over i) / nullif(stddev_pop(v) over i, 0), 0)",
    "zscore_col": "coalesce((v - avg(v) over s) / nullif(stddev_pop(v) over s, 0), 0)",
}


def sql_standardise(how: str) -> str:
    return f"with {duck.raw_slots(SLOTS)} select id, slot::bigint as slot, round({STANDARDS[how]}, 6) as v from grid window i as (partition by id), s as (partition by slot)"


def q_month_supplier(spark: SparkSession, d: str) -> DataFrame:
    lines = table(spark, d, "lineitem").select("l_suppkey", "l_shipdate", "l_quantity")
    built = profiles.grouped(lines, "l_suppkey", F.month("l_shipdate") - 1, "l_quantity", 12)
    nations = table(spark, d, "supplier").select(F.col("s_suppkey").cast("long").alias("id"), F.col("s_nationkey").cast("long").alias("party"))
    return built.join(nations, "id").select("party", "id", F.posexplode("y").alias("slot", "v")).select("party", "id", F.col("slot").cast("long").alias("slot"), F.round("v", 4).alias("v"))


SQL_MONTH_SUPPLIER = """with m as (select l_suppkey::bigint as id, month(l_shipdate) - 1 as slot, sum(l_quantity)::double as v from lineitem group by all)
select s_nationkey::bigint as party, u.id, r.s::bigint as slot, round(coalesce(m.v, 0), 4) as v
from (select distinct l_suppkey::bigint as id from lineitem) u join supplier on s_suppkey = u.id cross join range(12) r(s) left join m on m.id = u.id and m.slot = r.s"""


def q_part_month(spark: SparkSession, d: str) -> DataFrame:
    built = profiles.grouped(table(spark, d, "lineitem").select("l_partkey", "l_shipdate", "l_quantity"), "l_partkey", F.month("l_shipdate") - 1, "l_quantity", 12)
    brands = table(spark, d, "part").select(F.col("p_partkey").cast("long").alias("id"), F.col("p_brand").alias("party"))
    return built.join(brands, "id").groupBy("party").agg(F.count(F.lit(1)).alias("profiles"), *[F.round(F.sum(F.col("y")[i]), 4).alias(f"m{i}") for i in range(12)])


SQL_PART_MONTH = f"""with m as (select l_partkey, {", ".join(f"sum(case when month(l_shipdate) = {i + 1} then l_quantity else 0 end)::double as m{i}" for i in range(12))} from lineitem group by all)
select p_brand as party, count(*) as profiles, {", ".join(f"round(sum(m{i}), 4) as m{i}" for i in range(12))} from m join part on p_partkey = l_partkey group by all"""


def q_weekday_customer(spark: SparkSession, d: str) -> DataFrame:
    orders = table(spark, d, "orders").select("o_custkey", "o_orderdate", "o_totalprice")
    built = profiles.grouped(orders, "o_custkey", F.dayofweek("o_orderdate") - 1, "o_totalprice", 7)
    return built.select("id", F.posexplode("y").alias("slot", "v")).select("id", F.col("slot").cast("long").alias("slot"), F.round("v", 2).alias("v"))


SQL_WEEKDAY_CUSTOMER = """with m as (select o_custkey::bigint as id, dayofweek(o_orderdate) as slot, sum(o_totalprice) as v from orders group by all)
select u.id, r.s::bigint as slot, round(coalesce(m.v, 0), 2) as v from (select distinct o_custkey::bigint as id from orders) u cross join range(7) r(s) left join m on m.id = u.id and m.slot = r.s"""


# graphs -----------------------------------------------------------------------------------------------


def nation_edges(spark: SparkSession, d: str) -> DataFrame:
    """Circulant graph on nation keys: neighbours one and five keys away."""
    n = table(spark, d, "nation").select(F.col("n_nationkey").cast("int").alias("src"))
    return n.select("src", F.explode(F.array(*[F.pmod(F.col("src") + s, F.lit(25)).cast("int") for s in (1, 5, -1, -5)])).alias("dst")).distinct()


NATION_EDGES = "e as (select distinct n_nationkey::int as src, ((n_nationkey + s + 25) % 25)::int as dst from nation, (values (1), (5), (-1), (-5)) v(s))"
NATION_MIX = NATION_EDGES + """,
deg as (select src, count(*) as d from e group by src),
off as (select e.src, e.dst, 1.0::double / (1 + greatest(a.d, b.d)) as w from e join deg a on a.src = e.src join deg b on b.src = e.dst),
mix as (select * from off union all select src, src, 1 - sum(w) from off group by src)"""


def q_mixing_matrix(spark: SparkSession, d: str) -> DataFrame:
    return topology.mixing(nation_edges(spark, d)).select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.round("w", 9).alias("w"))


def q_boosted_matrix(spark: SparkSession, d: str) -> DataFrame:
    weights = topology.mixing(nation_edges(spark, d))
    boosted = topology.boost(weights, topology.optimal_boost(topology.matrix(weights)))
    return boosted.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"), F.round("w", 9).alias("w"))


#: The circulant's eigenvalues in closed form: every party keeps a fifth and gives a fifth to each of four neighbours.
SQL_BOOSTED = f"""with {NATION_MIX},
ev as (select k, (1 + 2 * cos(2 * pi() * k / 25) + 2 * cos(2 * pi() * 5 * k / 25)) / 5 as v from range(1, 25) r(k)),
a as (select (max(v) + min(v)) / (2 - max(v) - min(v)) as a from ev)
select src::bigint as src, dst::bigint as dst, round((1 + a.a) * w - case when src = dst then a.a else 0 end, 9) as w from mix, a"""


def q_degree_stats(spark: SparkSession, d: str) -> DataFrame:
    return topology.degree_stats(nation_edges(spark, d))


SQL_DEGREE_STATS = f"""with {NATION_EDGES}, deg as (select src, count(*) as d from e group by src)
select count(*) as parties, (sum(d) // 2)::bigint as edges, avg(d) as mean_degree, avg(d) + 1 as mean_extended, sum(d) / 2.0::double / count(*) as edges_per_party, max(d) as max_degree from deg"""


def q_exposed_pairs(spark: SparkSession, d: str) -> DataFrame:
    return topology.exposed(graphs.edges_df(spark, graphs.named("unsafe"))).select(F.col("watcher").cast("long").alias("watcher"), F.col("watched").cast("long").alias("watched"))


_UNSAFE = duck.values([e for a, b in graphs.named("unsafe") for e in ((a, b), (b, a))], "src, dst")
SQL_EXPOSED = f"""with e as (select * from {_UNSAFE}), n as (select src, dst from e union select src, src from e)
select e.src::bigint as watcher, e.dst::bigint as watched from e where not exists (select 1 from n where n.src = e.dst and n.dst not in (select dst from n m where m.src = e.src))"""


def q_components(spark: SparkSession, d: str) -> DataFrame:
    """Two rings of five, and a ring of a hundred parties."""
    pairs = graphs.named("split") + [(a + 100, b + 100) for a, b in graphs.ring(100)]
    return topology.connected_components(graphs.edges_df(spark, pairs)).select(F.col("src").cast("long").alias("party"), F.col("component").cast("long").alias("component"))


SQL_COMPONENTS = "select r::bigint as party, (case when r < 5 then 0 when r < 10 then 5 else 100 end)::bigint as component from (select r from range(10) t(r) union all select r + 100 from range(100) t(r))"


SPECTRA = ("circulant", "complete", "petersen", "ring")


def q_spectrum(spark: SparkSession, d: str) -> DataFrame:
    """Spectra of graphs whose eigenvalues are known in closed form."""
    rows = []
    for kind in SPECTRA:
        weights = topology.mixing(graphs.edges_df(spark, graphs.named(kind, 25 if kind == "circulant" else 10)))
        rows += [(kind, k, round(v, 6) + 0.0) for k, v in topology.spectrum(topology.matrix(weights)).items()]
    return spark.createDataFrame(rows, "graph string, measure string, value double")


SQL_SPECTRUM = """with ev as (select 'ring' as graph, (1 + 2 * cos(2 * pi() * k / 10)) / 3 as v from range(1, 10) r(k)
union all select 'circulant', (1 + 2 * cos(2 * pi() * k / 25) + 2 * cos(2 * pi() * 5 * k / 25)) / 5 from range(1, 25) r(k)
union all select 'complete', 0.0::double
union all select 'petersen', (1 + e) / 4.0::double from (values (1), (-2)) p(e)),
s as (select graph, max(v) as l2, min(v) as lm, (max(v) + min(v)) / (2 - max(v) - min(v)) as a from ev group by graph),
m as (select graph, any_value(l2) as lambda2, any_value(lm) as lambda_min, any_value(a) as a, max(abs(v)) as rho_plain, max(abs((1 + a) * v - a)) as rho_boosted from ev join s using (graph) group by graph)
select graph, measure, round(value, 6) + 0.0::double as value from (unpivot m on lambda2, lambda_min, a, rho_plain, rho_boosted into name measure value value)"""


def sweep(i: int, **how) -> consensus.Setting:
    """The i-th random graph of the sweep; its exposed edges stay, as in the reported experiment."""
    return consensus.Setting(graphs.random_connected(10, graphs.SWEEP_EDGES[i], i), 10, exposed="allow", **how)


def q_topology_degrees(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for i in range(len(graphs.SWEEP_EDGES)):
        one = topology.degree_stats(graphs.edges_df(spark, sweep(i).pairs)).withColumn("topology", F.lit(i + 1).cast("long"))
        out = one if out is None else out.unionByName(one)
    return out.withColumns({c: F.round(c, 6) for c in ("mean_degree", "mean_extended", "edges_per_party")})


SQL_TOPOLOGY_DEGREES = f"""with e as (select * from {duck.values([(i + 1, *e) for i in range(len(graphs.SWEEP_EDGES)) for a, b in sweep(i).pairs for e in ((a, b), (b, a))], "topology, src, dst")}),
deg as (select topology, src, count(*) as d from e group by all)
select topology::bigint as topology, count(*) as parties, (sum(d) // 2)::bigint as edges, round(avg(d), 6) as mean_degree, round(avg(d) + 1, 6) as mean_extended, round(sum(d) / 2.0::double / count(*), 6) as edges_per_party, max(d) as max_degree from deg group by topology"""


def q_topology_sweep(spark: SparkSession, d: str) -> DataFrame:
    """A masked k-means fit on each of nine random graphs: degrees, spectrum, the rounds its exchanges took until
    parties agreed, the rounds predicted, and the consensus seconds of a party."""
    df = settle(planted(spark, d, 48), "planted")
    rows = []
    for i, edges in enumerate(graphs.SWEEP_EDGES):
        s = sweep(i, stop="spread")
        sp = topology.spectrum(s.plain)
        _, r = cluster.fit_kmeans(df, cluster.public_peaks(6, 48)[0], s, iterations=3, stop="fixed", settled=True)
        rows.append((i + 1, edges, 2 * edges / 10, 2 * edges / 10 + 1, edges / 10, sp["lambda2"], sp["lambda_min"], sp["a"], sp["rho_boosted"], topology.rounds_needed(sp["rho_boosted"], s.beta), float(np.mean(r.rounds_per_iteration)), r.consensus_seconds / 10))
    discard(df)
    return spark.createDataFrame(rows, "topology int, edges int, mean_degree double, mean_extended double, edges_per_party double, lambda2 double, lambda_min double, a double, rho double, predicted int, rounds double, seconds double")


def ranks(v) -> np.ndarray:
    """Ranks, ties at their mean."""
    v = np.asarray(v, float)
    return (v[:, None] > v).sum(1) + ((v[:, None] == v).sum(1) - 1) / 2


def q_topology_trend(spark: SparkSession, d: str) -> DataFrame:
    """Whether rounds until agreement fall with the spectral radius over the nine graphs: rank correlation of both,
    for the payloads of a k-means fit as they are."""
    x, _ = consensus.dense(cluster.payloads(planted(spark, d, 48), [(KMeans(), Model(cluster.public_peaks(6, 48)[0]))]).where("comp >= 0"), 10)
    settings = [sweep(i, stop="spread") for i in range(len(graphs.SWEEP_EDGES))]
    rounds = [consensus.run_counted(x, s, s.nonce())[1] for s in settings]
    rank = float(np.corrcoef(ranks([s.rho for s in settings]), ranks(rounds))[0, 1])
    return spark.createDataFrame([(len(rounds), rank > 0.8, rounds[-1] < rounds[0] / 3)], "topologies long, rounds_follow_radius boolean, dense_graphs_are_faster boolean")


SQL_TOPOLOGY_TREND = "select 9::bigint as topologies, true as rounds_follow_radius, true as dense_graphs_are_faster"


# masks ------------------------------------------------------------------------------------------------


def q_mask_values(spark: SparkSession, d: str) -> DataFrame:
    return masking.mask_table(spark, SECRETS, "0", 20, 8).select(F.col("party").cast("long").alias("party"), F.col("comp").cast("long").alias("comp"), F.col("t").cast("long").alias("t"), F.round("delta", 9).alias("delta"))


_DRAWS = " union all ".join(f"select party, comp, {t}::bigint as t, {duck.draw('0', masking.SIGMA, masking.BETA, t)} as delta from range(10) a(party), range(20) b(comp)" for t in range(8))


def q_mask_telescopes(spark: SparkSession, d: str) -> DataFrame:
    grid = masking.mask_table(spark, SECRETS, "0", 20, 8)
    added = grid.withColumn("theta", masking.theta(masking.secret_of(SECRETS), F.lit("0"), F.col("party"), F.col("comp"), F.col("t")))
    return added.groupBy("party", "comp").agg(F.round(F.sum("theta"), 9).alias("added"), F.round(F.max_by("delta", "t"), 9).alias("last")).select(F.col("party").cast("long").alias("party"), F.col("comp").cast("long").alias("comp"), "added", "last")


SQL_TELESCOPES = f"with x as ({_DRAWS}) select party, comp, round(max_by(delta, t), 9) as added, round(max_by(delta, t), 9) as last from x group by all"


# consensus --------------------------------------------------------------------------------------------


def q_total(kind: str, spark: SparkSession, d: str, engine: str = "block", rounds: int = 90) -> DataFrame:
    s = setting(kind, stop="fixed", rounds=rounds)
    got = consensus.totals(first_states(spark, d), s, engine)
    return got.select(F.col("party").cast("long").alias("party"), F.col("comp").cast("long").alias("comp"), F.round("total", 6).alias("total"))


SQL_TOTAL = f"with {FIRST} select r.p::bigint as party, comp::bigint as comp, round(sum(x), 6) as total from start, range(10) r(p) group by all"
ROUNDS = 8


LONG = ("t", "party", "comp")


def q_trace(kind: str, spark: SparkSession, d: str, form: str = "matrix") -> DataFrame:
    out = consensus.run(first_states(spark, d), replayed(kind, stop="fixed", rounds=ROUNDS, form=form), "array", trace=True)
    return out.select(*[F.col(c).cast("long").alias(c) for c in LONG], F.round("shared", 6).alias("shared"), F.round("state", 6).alias("state"))


def sql_trace(kind: str) -> str:
    s = replayed(kind, stop="fixed", rounds=ROUNDS)
    rows = " union all ".join(f"select * from m{t}" for t in range(ROUNDS))
    return f"with {FIRST},\n{duck.trace('start', s.w, ROUNDS, s.sigma, s.beta)}\nselect t::bigint as t, party::bigint as party, comp::bigint as comp, round(shared, 6) as shared, round(state, 6) as state from ({rows})"


RACE = 60


def all_traces(spark: SparkSession, d: str, rounds: int = RACE) -> tuple[DataFrame, DataFrame]:
    """Traces of the four kinds from one start of 48 slots, and its exact totals."""
    start, out = settle(first_states(spark, d, 48), "start"), None
    for kind in consensus.KINDS:
        one = consensus.run(start, replayed(kind, stop="fixed", rounds=rounds), "block", trace=True).withColumn("kind", F.lit(kind))
        out = one if out is None else out.unionByName(one)
    return out, consensus.direct_sum(start)


def traces_sql(rounds: int = RACE) -> str:
    kinds = {k: (replayed(k, stop="fixed", rounds=rounds).w, masking.SIGMA if "masked" in k else 0.0) for k in consensus.KINDS}
    return f"with {first_sql(48)},\n{duck.traces('start', kinds, rounds, masking.BETA)}"


ERRORS = """,
total as (select comp, sum(x) as total from start group by comp),
per as (select kind, t, party, sqrt(sum((10 * state - total) ^ 2)) / sqrt(sum(total * total)) as e from all_m join total using (comp) group by all),
err as (select kind, t, avg(e) as mean_error, max(e) as max_error from per group by all)"""


def q_error_race(spark: SparkSession, d: str) -> DataFrame:
    race, exact = all_traces(spark, d)
    got = metrics.consensus_error(race, exact, 10)
    return got.select("kind", F.col("t").cast("long").alias("t"), F.round("mean_error", 9).alias("mean_error"), F.round("max_error", 9).alias("max_error"))


SQL_ERROR_RACE = f"{traces_sql()}{ERRORS}\nselect kind, t::bigint as t, round(mean_error, 9) as mean_error, round(max_error, 9) as max_error from err"


def q_rounds_to_eps(spark: SparkSession, d: str) -> DataFrame:
    race, exact = all_traces(spark, d)
    return metrics.rounds_to(metrics.consensus_error(race, exact, 10)).select("kind", F.col("rounds").cast("long").alias("rounds"))


SQL_ROUNDS_TO_EPS = f"{traces_sql()}{ERRORS}\nselect kind, min(t)::bigint as rounds from err where mean_error < 1e-6 group by kind"


def q_shared_by_first(spark: SparkSession, d: str) -> DataFrame:
    out = privacy.shared_trace(all_traces(spark, d, 20)[0], 0)
    return out.select("kind", *[F.col(c).cast("long").alias(c) for c in LONG], F.round("shared", 6).alias("shared"), F.round("state", 6).alias("state"))


SQL_SHARED_BY_FIRST = f"{traces_sql(20)}\nselect kind, t::bigint as t, party::bigint as party, comp::bigint as comp, round(shared, 6) as shared, round(state, 6) as state from all_m where party = 0"


def q_disagreement(spark: SparkSession, d: str) -> DataFrame:
    """How far apart parties still are after a few rounds, slot by slot."""
    got = metrics.spread(consensus.run(first_states(spark, d), replayed(stop="fixed", rounds=ROUNDS)))
    return got.select(F.col("comp").cast("long").alias("comp"), F.round("spread", 6).alias("spread"))


_LAST = replayed(stop="fixed", rounds=ROUNDS)
SQL_DISAGREEMENT = f"with {FIRST},\n{duck.trace('start', _LAST.w, ROUNDS, _LAST.sigma, _LAST.beta)}\nselect comp::bigint as comp, round(max(x) - min(x), 6) as spread from x{ROUNDS} group by comp"


def q_mask_gap(spark: SparkSession, d: str) -> DataFrame:
    trace = consensus.run(first_states(spark, d), replayed(stop="fixed", rounds=1), "array", trace=True)
    return privacy.mask_gap(trace).select(F.col("party").cast("long").alias("party"), F.col("comp").cast("long").alias("comp"), F.round("gap", 9).alias("gap"))


SQL_MASK_GAP = f"""with {FIRST} select party::bigint as party, comp::bigint as comp, round(abs({duck.draw('0', masking.SIGMA, masking.BETA, 0)}), 9) as gap from start"""


def q_messages(spark: SparkSession, d: str) -> DataFrame:
    trace = consensus.run(first_states(spark, d), setting(stop="fixed", rounds=3), "array", trace=True)
    sent = privacy.messages(trace, graphs.edges_df(spark, graphs.main_graph()))
    return sent.groupBy("src").agg(F.count(F.lit(1)).alias("floats"), F.countDistinct("dst").alias("neighbours")).withColumn("src", F.col("src").cast("long"))


_MAIN = duck.values([e for a, b in graphs.main_graph() for e in ((a, b), (b, a))], "src, dst")
SQL_MESSAGES = f"select src::bigint as src, count(*) * 3 * {SLOTS} as floats, count(*) as neighbours from (select * from {_MAIN}) group by src"


def q_direct_sum(spark: SparkSession, d: str) -> DataFrame:
    return consensus.direct_sum(first_states(spark, d)).select(F.col("comp").cast("long").alias("comp"), F.round("total", 6).alias("total"))


SQL_DIRECT = f"with {FIRST} select comp::bigint as comp, round(sum(x), 6) as total from start group by all"


def q_secure_shares(spark: SparkSession, d: str) -> DataFrame:
    state = first_states(spark, d).withColumn("x", F.round("x", 6))
    return secure.additive_shares(state, 10).select(F.col("comp").cast("long").alias("comp"), F.round("total", 6).alias("total"))


SQL_SHARES = f"with {FIRST} select comp::bigint as comp, round(sum(round(x, 6)), 6) as total from start group by all"


# clustering -------------------------------------------------------------------------------------------


def _rows(spark: SparkSession, model) -> DataFrame:
    df = cluster.model_df(spark, model).select("k", F.posexplode("mu").alias("slot", "mu"))
    return df.select(F.col("k").cast("long").alias("k"), F.col("slot").cast("long").alias("slot"), F.round("mu", 4).alias("mu"))


def q_kmeans(masked: bool, spark: SparkSession, d: str) -> DataFrame:
    df = planted(spark, d)
    model, _ = cluster.fit_kmeans(df, MU, setting(eps=1e-10) if masked else None, iterations=T, stop="fixed")
    sizes = metrics.sizes(cluster.assign_hard(df, model.mu)).select(F.col("k").cast("long").alias("k"), "n")
    return _rows(spark, model).join(F.broadcast(sizes), "k", "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("long"))


def _kmeans_sql(where: str = "") -> str:
    source = duck.planted(SLOTS) if not where else duck.planted(SLOTS).replace("\np as (", "\nall_p as (") + f",\np as (select * from all_p where {where})"
    return f"with {source},\n{duck.kmeans(MU, T)}\nselect m.k::bigint as k, m.slot::bigint as slot, round(m.mu, 4) as mu, (select count(*) from a{T} a where a.k = m.k) as n from m{T} m"


def q_kmeans_single(spark: SparkSession, d: str) -> DataFrame:
    df = planted(spark, d).where("party = 0")
    model, _ = cluster.fit_kmeans(df, MU, iterations=T, stop="fixed")
    sizes = metrics.sizes(cluster.assign_hard(df, model.mu)).select(F.col("k").cast("long").alias("k"), "n")
    return _rows(spark, model).join(F.broadcast(sizes), "k", "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("long"))


def q_fuzzy(weighting: str, masked: bool, spark: SparkSession, d: str) -> DataFrame:
    return _rows(spark, cluster.fit_fuzzy(planted(spark, d), MU, setting(eps=1e-10) if masked else None, weighting=weighting, iterations=T, stop="fixed")[0])


def sql_fuzzy(weighting: str) -> str:
    return f"with {duck.planted(SLOTS)},\n{duck.fuzzy(MU, T, 2 if weighting == 'classical' else 1)}\nselect k::bigint as k, slot::bigint as slot, round(mu, 4) as mu from m{T}"


def q_gmm_diag(masked: bool, spark: SparkSession, d: str) -> DataFrame:
    model, _ = cluster.fit_gmm(planted(spark, d), MU, setting(eps=1e-10) if masked else None, cov="diag", variance=0.1, reg=1e-4, iterations=T, stop="fixed")
    df = cluster.model_df(spark, model).select("k", "weight", F.explode(F.arrays_zip(F.sequence(F.lit(0), F.lit(SLOTS - 1)).alias("slot"), F.col("mu").alias("mu"), F.col("sigma").alias("var"))).alias("c"))
    return df.select(F.col("k").cast("long").alias("k"), F.col("c.slot").cast("long").alias("slot"), F.round("c.mu", 4).alias("mu"), F.round("c.var", 4).alias("var"), F.round("weight", 4).alias("weight"))


SQL_GMM_DIAG = f"with {duck.planted(SLOTS)},\n{duck.gmm_diag(MU, T, 0.1, 1e-4)}\nselect m.k::bigint as k, m.slot::bigint as slot, round(m.mu, 4) as mu, round(m.var, 4) as var, round(w.weight, 4) as weight from m{T} m join w{T} w on w.k = m.k"


def q_gmm_full(masked: bool, spark: SparkSession, d: str) -> DataFrame:
    model, report = cluster.fit_gmm(planted(spark, d), MU, setting() if masked else None, cov="full", variance=0.1, reg=1e-4, iterations=T, stop="fixed")
    return _rows(spark, model).withColumn("log_likelihood", F.lit(round(report.objective[-1], 2)))


def q_entry(spark: SparkSession, d: str) -> DataFrame:
    """The flagship: masked k-means of half-hour profiles over ten parties."""
    df = settle(peak(spark, d, 48), "profiles")
    s = setting()
    mu = cluster.masked_start(df, 2, s)
    model, _ = cluster.fit_kmeans(df, mu, s, iterations=10, settled=True)
    sizes = metrics.sizes(cluster.assign_hard(df, model.mu))
    return cluster.model_df(spark, model).select("k", "mu").join(sizes, "k", "left").select("k", F.coalesce("n", F.lit(0)).alias("size"), "mu")


def q_kmeans_wide(spark: SparkSession, d: str, copies: int = 10) -> DataFrame:
    """Masked k-means of many times as many planted consumers (copies for each customer): iterations, rows, counts."""
    df = settle(tables.planted(spark, d, SLOTS, copies=copies).select("party", "id", "y"), "wide")
    model, report = cluster.fit_kmeans(df, cluster.public_peaks(6, SLOTS)[0], setting(eps=1e-10), iterations=T, stop="fixed", settled=True)
    sizes = metrics.sizes(cluster.assign_hard(df, model.mu))
    return sizes.select(F.col("k").cast("long").alias("k"), "n", F.lit(report.iterations).cast("long").alias("iterations"))


def q_soft(family_name: str, spark: SparkSession, d: str) -> DataFrame:
    """Memberships or responsibilities under the start model."""
    df = planted(spark, d)
    family = FuzzyCMeans() if family_name == "fuzzy" else GaussianMixture("diag")
    model = cluster.Model(MU) if family_name == "fuzzy" else family.start(MU, 0.1)
    got = cluster.assign_shares(df, family, model).select("id", F.posexplode("u").alias("k", "u"))
    return got.select("id", F.col("k").cast("long").alias("k"), F.round("u", 5).alias("u"))


SQL_SOFT_FUZZY = f"with {duck.planted(SLOTS)},\n{duck.fuzzy(MU, 1, 1)}\nselect id, k::bigint as k, round(g, 5) as u from u0"
SQL_SOFT_GMM = f"with {duck.planted(SLOTS)},\n{duck.gmm_diag(MU, 1, 0.1, 1e-4)}\nselect id, k::bigint as k, round(q, 5) as u from q0"


def q_assign(spark: SparkSession, d: str) -> DataFrame:
    return cluster.assign_hard(planted(spark, d), MU).select("id", F.col("k").cast("long").alias("k"))


SQL_ASSIGN = f"with {duck.planted(SLOTS)},\n{duck.kmeans(MU, 0)}\nselect id, k::bigint as k from a0"


def summaries(spark: SparkSession, d: str) -> DataFrame:
    """(party, k, z, s) raw local summaries in SQL functions."""
    a = cluster.assign_hard(planted(spark, d), MU)
    return a.groupBy("party", "k").agg(F.count(F.lit(1)).cast("double").alias("z"), F.array(*[F.sum(F.col("y")[i]) for i in range(SLOTS)]).alias("s"))


def q_local_summary(spark: SparkSession, d: str) -> DataFrame:
    return summaries(spark, d).select(F.col("party").cast("long").alias("party"), F.col("k").cast("long").alias("k"), F.col("z").cast("long").alias("z"), F.posexplode("s").alias("slot", "s")).select("party", "k", "z", F.col("slot").cast("long").alias("slot"), F.round("s", 5).alias("s"))


_A0 = f"with {duck.planted(SLOTS)},\n{duck.kmeans(MU, 0)},\nsm as (select a.party, a.k, p.slot, count(*)::double as z, sum(p.y) as s from a0 a join p on p.id = a.id group by all)"
SQL_LOCAL = f"{_A0} select party::bigint as party, k::bigint as k, z::bigint as z, slot::bigint as slot, round(s, 5) as s from sm"


def q_disclose(what: str, spark: SparkSession, d: str) -> DataFrame:
    seen = privacy.disclose(summaries(spark, d)).withColumns({c: F.col(c).cast("long") for c in ("party", "k", "n")})
    if what == "count":
        return seen.select("party", "n").distinct()
    if what == "proportion":
        return seen.select("party", "k", F.round("ratio", 6).alias("ratio"))
    return seen.select("party", "k", F.posexplode("mu").alias("slot", "mu")).select("party", "k", F.col("slot").cast("long").alias("slot"), F.round("mu", 5).alias("mu"))


SQL_DISCLOSE = {
    "count": f"{_A0} select party::bigint as party, sum(z)::bigint as n from sm where slot = 0 group by all",
    "proportion": f"{_A0} select party::bigint as party, k::bigint as k, round(z / sum(z) over (partition by party), 6) as ratio from sm where slot = 0",
    "centroid": f"{_A0} select party::bigint as party, k::bigint as k, slot::bigint as slot, round(s / z, 5) as mu from sm",
}


# measures ---------------------------------------------------------------------------------------------


def by_archetype(spark: SparkSession, d: str) -> DataFrame:
    return tables.planted(spark, d, SLOTS).select("party", "id", F.col("archetype").alias("k"), "y")


def q_silhouette(how: str, spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(round(metrics.silhouette(by_archetype(spark, d), how), 6),)], "silhouette double")


def sql_silhouette(how: str) -> str:
    dist = "sqrt(sum((a.y - b.y) ^ 2))" if how == "exact" else "sum((a.y - b.y) ^ 2)"
    return f"""with {duck.planted(SLOTS)},
v as (select id, archetype as k, list(y order by slot) as y from p group by all),
dd as (select a.id, a.k as own, b.k as other, {"sqrt" if how == "exact" else ""}(list_sum(list_transform(list_zip(a.y, b.y), lambda z: (z[1] - z[2]) ^ 2))) as dist from v a, v b where a.id <> b.id),
t as (select id, own, other, avg(dist) as m from dd group by all),
s as (select id, max(m) filter (own = other) as a, min(m) filter (own <> other) as b from t group by all)
select round(avg((b - a) / greatest(a, b)), 6) as silhouette from s"""


def q_sse(spark: SparkSession, d: str) -> DataFrame:
    a = by_archetype(spark, d)
    mu = a.groupBy("k").agg(F.array(*[F.avg(F.col("y")[i]) for i in range(SLOTS)]).alias("mu"))
    return metrics.sse(a, mu).select(F.round("sse", 4).alias("sse"))


SQL_SSE = f"with {duck.planted(SLOTS)}, m as (select archetype, slot, avg(y) as mu from p group by all) select round(sum((y - mu) ^ 2), 4) as sse from p join m using (archetype, slot)"


KS = tuple(range(2, 11))
GMM = {"variance": 0.1, "reg": 1e-3}


def three_families(mu: np.ndarray) -> list[tuple[str, object, Model]]:
    """The three families from one start; mixtures here with diagonal covariances, which SQL can follow."""
    mixture = GaussianMixture("diag", reg=GMM["reg"])
    return [("kmeans", KMeans(), Model(mu)), ("fuzzy", FuzzyCMeans(), Model(mu)), ("gmm", mixture, mixture.start(mu, GMM["variance"]))]


def carriers(spark: SparkSession, d: str, slots: int, names: tuple[str, ...] = ("planted", "events")) -> dict[str, DataFrame]:
    made = {"planted": planted, "events": peak}
    return {name: settle(made[name](spark, d, slots), name) for name in names}


def q_silhouette_by_k(spark: SparkSession, d: str) -> DataFrame:
    """Silhouette for K = 2..10 of three families, centralised and masked, on planted and event profiles, after
    T iterations from public starts. All fits of a carrier share their scans."""
    rows = []
    for carrier, df in carriers(spark, d, SLOTS).items():
        parts = [(name, k, family, model) for k in KS for name, family, model in three_families(cluster.public_peaks(k, SLOTS)[0])]
        for where, s in (("central", None), ("masked", setting(eps=1e-10))):
            fitted = cluster.fit_many(df, [(f, m) for _, _, f, m in parts], s, iterations=T, stop="fixed", settled=True)
            scores = metrics.silhouettes(df, [(p[2], m) for p, (m, _) in zip(parts, fitted)])
            rows += [(carrier, p[0], where, p[1], round(v, 4)) for p, v in zip(parts, scores)]
        discard(df)
    return spark.createDataFrame(rows, "carrier string, family string, kind string, k long, silhouette double")


def both_carriers(slots: int) -> str:
    """p(src, id, slot, y) of planted and event profiles."""
    one, two = duck.planted(slots).replace("\np as (", "\np1 as ("), duck.peak_profiles(slots).replace("\np as (", "\np2 as (")
    return f"{one},\n{two},\np as materialized (select 'planted' as src, id, slot, y from p1 union all select 'events', id, slot, y from p2)"


def _silhouette_by_k_sql() -> str:
    g = {10 * k + i: (src, k) for k in KS for i, src in enumerate(("planted", "events"))}
    starts = {n: cluster.public_peaks(k, SLOTS)[0] for n, (_, k) in g.items()}
    made = {"kmeans": ("km", duck.many_kmeans("km", starts, T)), "fuzzy": ("fz", duck.many_fuzzy("fz", starts, T)), "gmm": ("gm", duck.many_gmm("gm", starts, T, GMM["variance"], GMM["reg"]))}
    parts = ",\n".join(f"{sql},\n{duck.silhouettes(pre)}" for pre, sql in made.values())
    out = " union all ".join(f"select src as carrier, '{name}' as family, kind, (g // 10)::bigint as k, round(silhouette, 4) as silhouette from {pre}sil join fits using (g), (values ('central'), ('masked')) v(kind)" for name, (pre, _) in made.items())
    return f"with {both_carriers(SLOTS)},\n{duck.fits({n: src for n, (src, _) in g.items()})},\n{parts}\n{out}"


def own_start(df: DataFrame, k: int, pool: int = 300, tries: int = 20) -> np.ndarray:
    """A party's start from its own rows, which it need not publish: the best of several seeded k-means runs on
    `pool` of them (at each, new centroids are drawn by distance from those there are)."""
    rows = cluster.sample_rows(df, pool)
    best, least = rows[:k], np.inf
    for seed in range(tries):
        rng = np.random.default_rng(seed)
        mu = rows[[rng.integers(len(rows))]]
        while len(mu) < k:
            d2 = ((rows[:, None] - mu) ** 2).sum(2).min(1)
            mu = np.vstack([mu, rows[rng.choice(len(rows), p=d2 / d2.sum())]])
        for _ in range(10):
            near = ((rows[:, None] - mu) ** 2).sum(2).argmin(1)
            mu = np.array([rows[near == c].mean(0) if (near == c).any() else mu[c] for c in range(k)])
        f = ((rows[:, None] - mu) ** 2).sum(2).min(1).sum()
        if f < least:
            best, least = mu, f
    return best


def q_sse_by_k(spark: SparkSession, d: str) -> DataFrame:
    """Squared error for K = 1..9 on the union (masked, from public starts) and on party 0 alone, with the chosen K."""
    df, ks, rows = settle(planted(spark, d, 48), "planted"), list(range(1, 10)), []
    alone = df.where("party = 0")
    for scope, part, s, starts in (("union", df, setting(), lambda k: cluster.public_peaks(k, 48, 6)), ("party 0", alone, None, lambda k: [own_start(alone, k)])):
        best, values = cluster.select_k(part, ks, starts, s, "second_diff", iterations=100, stop="objective", tol=1e-4, settled=True)
        rows += [(scope, k, float(v), best) for k, v in zip(ks, values)]
    discard(df)
    return spark.createDataFrame(rows, "scope string, k int, sse double, chosen int")


def q_missed_patterns(spark: SparkSession, d: str) -> DataFrame:
    """Consumers whose union pattern party 0 does not know, against the centroids it finds alone."""
    df = settle(planted(spark, d, 48), "planted")
    alone = df.where("party = 0")
    union, _ = cluster.best_of(df, KMeans(), [Model(mu) for mu in cluster.public_peaks(6, 48, 6)], setting(), iterations=200, tol=1e-3, settled=True)
    single, _ = cluster.fit_kmeans(alone, own_start(alone, 2), iterations=200, tol=1e-3, settled=True)
    known = metrics.patterns_known(single.mu, union.mu)
    return metrics.missed(cluster.assign_hard(df, union.mu), known).agg(F.count(F.lit(1)).alias("missed"))


SQL_MISSED = "select count(*) as missed from customer where c_custkey % 6 not in (1, 2)"
PATTERNS = cluster.public_peaks(6, 48)[0]


def q_union_patterns(masked: bool, spark: SparkSession, d: str) -> DataFrame:
    """Six half-hour patterns of the union and their sizes, after T iterations from a public start."""
    df = settle(planted(spark, d, 48), "planted")
    model, _ = cluster.fit_kmeans(df, PATTERNS, setting(eps=1e-10) if masked else None, iterations=T, stop="fixed", settled=True)
    sizes = metrics.sizes(cluster.assign_hard(df, model.mu)).select(F.col("k").cast("long").alias("k"), "n")
    return _rows(spark, model).join(F.broadcast(sizes), "k", "left").withColumn("n", F.coalesce("n", F.lit(0)).cast("long"))


SQL_UNION_PATTERNS = f"""with {duck.planted(48).replace(chr(10) + "p as (", chr(10) + "p1 as (")},
p as materialized (select 'union' as src, id, slot, y from p1),\n{duck.fits({1: "union"})},\n{duck.many_kmeans("km", {1: PATTERNS}, T)}
select m.k::bigint as k, m.slot::bigint as slot, round(m.mu, 4) as mu, (select count(*) from kma a where a.k = m.k) as n from kmm{T} m"""


def q_cluster_sizes(spark: SparkSession, d: str) -> DataFrame:
    return metrics.sizes(cluster.assign_hard(planted(spark, d), MU)).select(F.col("k").cast("long").alias("k"), "n")


SQL_SIZES = f"with {duck.planted(SLOTS)},\n{duck.kmeans(MU, 0)}\nselect k::bigint as k, count(*) as n from a0 group by all"


def q_centroid_gap(spark: SparkSession, d: str) -> DataFrame:
    """Distance of the masked union's centroids from the centralised ones, and from those of party 0 alone."""
    df = settle(planted(spark, d), "planted")
    how = {"iterations": T, "stop": "fixed", "settled": True}
    central, masked = (cluster.fit_kmeans(df, MU, s, **how)[0].mu for s in (None, setting(eps=1e-10)))
    alone = cluster.fit_kmeans(df.where("party = 0"), MU, **how)[0].mu
    discard(df)
    rows = [("central", round(metrics.centroid_gap(masked, central), 4)), ("party 0", round(metrics.centroid_gap(masked, alone), 4))]
    return spark.createDataFrame(rows, "against string, gap double")


SQL_CENTROID_GAP = f"""with {duck.planted(SLOTS).replace(chr(10) + "p as (", chr(10) + "p1 as (")},
p as materialized (select 'union' as src, id, slot, y from p1 union all select 'party 0', id, slot, y from p1 where party = 0),
{duck.fits({1: "union", 2: "party 0"})},\n{duck.many_kmeans("km", {1: MU, 2: MU}, T)},
gaps as (select u.k as a, o.k as b, o.g, sqrt(sum((u.mu - o.mu) ^ 2)) as dist from kmm{T} u join kmm{T} o on o.slot = u.slot where u.g = 1 group by all),
near as (select g, min(dist) as m from gaps group by g, a union all select g, min(dist) from gaps group by g, b)
select case g when 1 then 'central' else 'party 0' end as against, round(max(m), 4) as gap from near group by g"""


def q_parity(spark: SparkSession, d: str) -> DataFrame:
    """Rows that central and masked fits put in the same cluster."""
    df = peak(spark, d)
    a, _ = cluster.fit_kmeans(df, MU, iterations=T, stop="fixed")
    b, _ = cluster.fit_kmeans(df, MU, setting(eps=1e-9), iterations=T, stop="fixed")
    return metrics.parity(cluster.assign_hard(df, a.mu), cluster.assign_hard(df, b.mu))


SQL_PARITY = "select count(distinct user_id) as n, count(distinct user_id) as equal from events"


def q_objectives(spark: SparkSession, d: str) -> DataFrame:
    df = planted(spark, d)
    rows = []
    for name, family, model in (("kmeans", KMeans(), cluster.Model(MU)), ("fuzzy", FuzzyCMeans(), cluster.Model(MU)), ("gmm", GaussianMixture("diag"), GaussianMixture("diag").start(MU, 0.1))):
        last = cluster.payloads(df, [(family, model)], pooled=True).orderBy(F.desc("comp")).first()
        rows.append((name, round(last["x"], 3)))
    return spark.createDataFrame(rows, "family string, objective double")


SQL_OBJECTIVES = f"""with {duck.planted(SLOTS)},\n{duck.fuzzy(MU, 1, 2)},
lg as (select p.id, m.k, ln({1 / K!r}) - 0.5 * sum(ln(2 * pi()) + ln(0.1) + (p.y - m.mu) ^ 2 / 0.1) as l from p join m0 m on m.slot = p.slot group by all)
select 'kmeans' as family, round(sum(d), 3) as objective from (select min(d2) as d from d0 group by id)
union all select 'fuzzy', round(sum(u.g * d0.d2), 3) from u0 u join d0 on d0.id = u.id and d0.k = u.k
union all select 'gmm', round(sum(s), 3) from (select ln(sum(exp(l))) as s from lg group by id)"""


def fits_to_the_end(spark: SparkSession, d: str, slots: int, k: int, cov: str, tol: float, iterations: int, names: tuple[str, ...] = ("planted", "events")) -> list[tuple]:
    """(carrier, family, kind, setting, report) of all families, centralised and masked, until centroids rest."""
    out = []
    for carrier, df in carriers(spark, d, slots, names).items():
        mu, mixture = cluster.public_peaks(k, slots)[0], GaussianMixture(cov, reg=1e-3)
        parts = [(KMeans(), Model(mu)), (FuzzyCMeans(), Model(mu)), (mixture, mixture.start(mu, 0.1))]
        for kind, s in (("central", None), ("masked", setting(eps=1e-9))):
            for (family, _), (_, report) in zip(parts, cluster.fit_many(df, parts, s, iterations=iterations, tol=tol, settled=True)):
                out.append((carrier, family.name, kind, s, report))
        discard(df)
    return out


def q_times(spark: SparkSession, d: str, names: tuple[str, ...] = ("planted", "events")) -> DataFrame:
    """Seconds and iterations of three families to convergence, centralised and masked over ten parties (the latter:
    the slowest party, without communication)."""
    rows = []
    for carrier, name, kind, s, r in fits_to_the_end(spark, d, 48, 6, "full", 1e-3, 300, names):
        local = r.party_seconds.values()
        rows.append((carrier, name, kind, r.iterations, r.converged, float(sum(local) if s is None else max(local)), r.consensus_seconds / (s.parties if s else 1)))
    return spark.createDataFrame(rows, "carrier string, family string, kind string, iterations int, converged boolean, local_seconds double, consensus_seconds double")


def q_iteration_parity(spark: SparkSession, d: str) -> DataFrame:
    """Whether masked fits take as many iterations as centralised ones, and all converge."""
    got = {(c, f, k): r for c, f, k, _, r in fits_to_the_end(spark, d, 48, 6, "full", 1e-3, 300)}
    rows = [(c, f, got[c, f, "masked"].iterations == r.iterations, r.converged and got[c, f, "masked"].converged) for (c, f, k), r in got.items() if k == "central"]
    return spark.createDataFrame(rows, "carrier string, family string, equal boolean, converged boolean")


SQL_ITERATION_PARITY = "select carrier, family, true as equal, true as converged from (values ('planted'), ('events')) c(carrier), (values ('kmeans'), ('fuzzy'), ('gmm')) f(family)"


def q_payload_cost(spark: SparkSession, d: str) -> DataFrame:
    rows = [(f, k, 48, cost.payload(f, k, 48), cost.message_bytes(cost.payload(f, k, 48))) for f in ("fuzzy", "gmm", "kmeans") for k in (2, 6)]
    return spark.createDataFrame(rows, "family string, k long, d long, floats long, bytes long")


SQL_PAYLOAD = """select family, k::bigint as k, 48::bigint as d, (k * case family when 'gmm' then 1 + 48 + 48 * 49 // 2 else 49 end)::bigint as floats, (4 * k * case family when 'gmm' then 1 + 48 + 48 * 49 // 2 else 49 end)::bigint as bytes
from (values ('fuzzy'), ('gmm'), ('kmeans')) f(family), (values (2), (6)) g(k)"""


def q_upload_cost(spark: SparkSession, d: str) -> DataFrame:
    size = cost.upload_bytes(cost.payload("kmeans", 6, 48), 5, 27, 7)
    rows = [(r, size, round(size / 1024, 2), round(cost.link_seconds(size, r), 4)) for r in (11.03, 55.18)]
    return spark.createDataFrame(rows, "mbit_s double, bytes long, kib double, seconds double")


SQL_UPLOAD = "select r::double as mbit_s, (6 * 49 * 4 * 5 * 27 * 7)::bigint as bytes, round(6 * 49 * 4 * 5 * 27 * 7 / 1024.0::double, 2) as kib, round(6 * 49 * 4 * 5 * 27 * 7 * 8 / (r::double * 1e6), 4) as seconds from (values (11.03), (55.18)) v(r)"


def q_upload_measured(spark: SparkSession, d: str) -> DataFrame:
    """What the busiest party of the main graph sends in a masked k-means fit to convergence, from its measured
    rounds and iterations, and the seconds that takes."""
    s = setting()
    _, r = cluster.fit_kmeans(planted(spark, d, 48), PATTERNS, s, tol=1e-3, iterations=300)
    degree = int((s.plain > 0).sum(1).max()) - 1
    rounds = sum(r.rounds_per_iteration)
    size = cost.message_bytes(r.payload_floats) * degree * rounds
    rows = [(m, r.payload_floats, degree, r.iterations, rounds, size, cost.link_seconds(size, m)) for m in (11.03, 55.18)]
    return spark.createDataFrame(rows, "mbit_s double, floats long, degree long, iterations long, rounds long, bytes long, seconds double")


def q_multiplications(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for mode in ("paper_formula", "per_component"):
        got = cost.multiplications(1000, 100, 6, 48, 5, 27, 7, mode)
        rows += [(mode, what, float(v)) for what, v in got.items()]
    return spark.createDataFrame(rows, "mode string, part string, products double")


SQL_MULTIPLICATIONS = """select mode, part, (case part when 'central' then 1000 * 6 * 7 * d when 'party_local' then 100 * 6 * 7 * d else 6 * 27 * 7 * f end)::double as products
from (values ('paper_formula', 1, 1), ('per_component', 48, 294)) m(mode, d, f), (values ('central'), ('party_local'), ('party_consensus')) p(part)"""


def q_audit(spark: SparkSession, d: str) -> DataFrame:
    """Rounding attack at the defaults and with masks scaled to the counts; rebuilding over an exposed and a safe
    edge; draws of others guessed with one's own secret, and draws that come back in later exchanges."""
    rng = np.random.default_rng(0)
    counts, x = rng.integers(0, 60, (10, 6)).astype(float), rng.normal(size=(10, 6))
    s, wide = setting(), setting(scale=60.0)
    bad = consensus.Setting(graphs.named("unsafe"), 10, exposed="allow")
    rows = [
        ("rounded counts", privacy.count_rounding_attack(counts, s)),
        ("rounded counts, scaled", privacy.count_rounding_attack(counts, wide)),
        ("rebuild error, exposed edge", float(np.abs(privacy.rebuild(x, bad, 0, 1) - x[1]).max())),
        ("rebuild error, safe edge", float(np.abs(privacy.rebuild(x, s, 0, 5) - x[5]).max())),
        ("repeated draws, 1", privacy.repeated_draws(5.0, s, 1)),
        ("repeated draws, 50", privacy.repeated_draws(5.0, s, 50)),
        ("guessed masks", privacy.guessed_masks(s, 0)),
        ("shared draws", float(privacy.shared_draws(s, 50))),
    ]
    return spark.createDataFrame(rows, "audit string, value double")


# heterogeneous workloads -------------------------------------------------------------------------------


def q_embedding_parties(spark: SparkSession, d: str) -> DataFrame:
    """Non-identical parties: labels hold the vectors; masked k-means with 64 dimensions against central."""
    df = table(spark, d, "embeddings").select(F.col("label").cast("int").alias("party"), F.col("vec_id").alias("id"), F.expr("transform(embedding, v -> cast(v as double))").alias("y"))
    mu = cluster.public_random(4, 64, "emb", 0.2, -0.1)
    a, _ = cluster.fit_kmeans(df, mu, iterations=3, stop="fixed")
    b, _ = cluster.fit_kmeans(df, mu, setting(eps=1e-9), iterations=3, stop="fixed")
    return metrics.parity(cluster.assign_hard(df, a.mu), cluster.assign_hard(df, b.mu))


SQL_EMBEDDING_PARTIES = "select count(*) as n, count(*) as equal from embeddings"


def q_nation_parties(spark: SparkSession, d: str) -> DataFrame:
    """25 nations as parties on a circulant graph: total slot energy of each nation's customers' readings."""
    users = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("user_id"), F.col("c_nationkey").cast("int").alias("party"))
    slots = tables.readings(spark, d).withColumn("comp", tables.slot_of("ts", SLOTS)).join(users, "user_id")
    state = slots.groupBy("party", "comp").agg(F.sum("value").alias("x"))
    s = consensus.Setting(graphs.circulant(25, (1, 5)), 25, stop="fixed", rounds=120)
    return consensus.totals(state, s).where("party = 0").select(F.col("comp").cast("long").alias("comp"), F.round("total", 3).alias("total"))


SQL_NATION_PARTIES = "select ((hour(ts) * 60 + minute(ts)) // 120)::bigint as comp, round(sum(value), 3) as total from events join customer on c_custkey = user_id group by all"


NATION_MU = cluster.public_peaks(K, SLOTS)[0]


def q_nation_kmeans(spark: SparkSession, d: str) -> DataFrame:
    """Masked k-means of the readings' profiles with 25 nations as parties."""
    nation = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("id"), F.col("c_nationkey").cast("int").alias("party"))
    df = peak(spark, d).drop("party").join(nation, "id").select("party", "id", "y")
    s = consensus.Setting(graphs.circulant(25, (1, 5)), 25, eps=1e-10)
    return _rows(spark, cluster.fit_kmeans(df, NATION_MU, s, iterations=T, stop="fixed")[0])


SQL_NATION_KMEANS = f"""with {duck.peak_profiles(SLOTS).replace(chr(10) + "p as (", chr(10) + "p1 as (")},\np as (select p1.* from p1 join customer on c_custkey = id),
{duck.kmeans(NATION_MU, T)}\nselect k::bigint as k, slot::bigint as slot, round(mu, 4) as mu from m{T}"""


TEXT_MU = np.array([[5.0, 3.0, 0.0, 1.0], [7.5, 6.0, 0.0, 2.0], [9.5, 8.0, 0.0, 4.0]])


def q_text_features(spark: SparkSession, d: str) -> DataFrame:
    """Documents as small profiles (length, words, share of digits, lines), their sources as parties of a ring:
    masked k-means, cluster sizes, and the purity of the clusters against labelled quality."""
    text, sources = F.coalesce("text", F.lit("")), table(spark, d, "documents").select("source").distinct()
    names = sorted(r[0] or "" for r in sources.collect())  # a party each
    party = F.coalesce(F.array_position(F.array(*map(F.lit, names)), F.coalesce("source", F.lit(""))) - 1, F.lit(0)).cast("int")

    def marks(pattern: str):
        return F.length(text) - F.length(F.regexp_replace(text, pattern, ""))

    y = F.array(F.log1p(F.length(text).cast("double")), F.log1p((marks(" ") + 1).cast("double")), marks("[0-9]") / F.greatest(F.length(text), F.lit(1)), F.log1p((marks("\n") + 1).cast("double")))
    df = settle(table(spark, d, "documents").select(party.alias("party"), F.col("doc_id").alias("id"), y.alias("y")), "features")
    s = consensus.Setting(graphs.ring(len(names)), len(names), eps=1e-10)
    model, _ = cluster.fit_kmeans(df, TEXT_MU, s, iterations=T, stop="fixed", settled=True)
    assigned = cluster.assign_hard(df, model.mu)
    labelled = assigned.join(table(spark, d, "labels").select(F.col("doc_id").alias("id"), "quality"), "id")
    return metrics.sizes(assigned).crossJoin(F.broadcast(metrics.purity(labelled, "quality"))).select(F.col("k").cast("long").alias("k"), "n", F.round("purity", 6).alias("purity"))


SQL_TEXT_FEATURES = f"""with t as (select doc_id as id, coalesce(text, '') as x from documents),
f as (select id, [ln(1 + length(x)::double), ln(2 + length(x) - length(replace(x, ' ', ''))::double), (length(x) - length(regexp_replace(x, '[0-9]', '', 'g')))::double / greatest(length(x), 1), ln(2 + length(x) - length(replace(x, chr(10), ''))::double)] as v from t),
p as materialized (select 0 as party, id, s as slot, v[s + 1] as y from f, range(4) r(s)),
{duck.kmeans(TEXT_MU, T)},
lab as (select a.k, l.quality, count(*) as n from a{T} a join labels l on l.doc_id = a.id group by all),
pur as (select sum(top)::double / sum(n) as purity from (select max(n) as top, sum(n) as n from lab group by k))
select k::bigint as k, count(*) as n, round(any_value(purity), 6) as purity from a{T}, pur group by k"""


def build() -> dict[str, tuple]:
    q: dict[str, tuple] = {}
    q["kmeans_masked"] = (partial(q_kmeans, True), _kmeans_sql())
    q["kmeans_central"] = (partial(q_kmeans, False), _kmeans_sql())
    q["kmeans_single_party"] = (q_kmeans_single, _kmeans_sql("party = 0"))
    for weighting in ("classical", "as_printed"):
        for masked in (True, False):
            q[f"fuzzy_{weighting}_{'masked' if masked else 'central'}"] = (partial(q_fuzzy, weighting, masked), sql_fuzzy(weighting))
    for masked in (True, False):
        q[f"gmm_diag_{'masked' if masked else 'central'}"] = (partial(q_gmm_diag, masked), SQL_GMM_DIAG)
        q[f"gmm_full_{'masked' if masked else 'central'}"] = (partial(q_gmm_full, masked), None)
    for how in ("sum", "mean", "median", "trimmed_mean"):
        q[f"profile_{how}"] = (partial(q_profile, how, 48), sql_profile(how, 48))
    for how in STANDARDS:
        q[f"standardise_{how}"] = (partial(q_standardise, how), sql_standardise(how))
    q["profile_month_supplier"] = (q_month_supplier, SQL_MONTH_SUPPLIER)
    q["profile_month_part"] = (q_part_month, SQL_PART_MONTH)
    q["profile_weekday_customer"] = (q_weekday_customer, SQL_WEEKDAY_CUSTOMER)
    q["mixing_matrix"] = (q_mixing_matrix, f"with {NATION_MIX} select src::bigint as src, dst::bigint as dst, round(w, 9) as w from mix")
    q["boosted_matrix"] = (q_boosted_matrix, SQL_BOOSTED)
    q["degree_stats"] = (q_degree_stats, SQL_DEGREE_STATS)
    q["exposed_pairs"] = (q_exposed_pairs, SQL_EXPOSED)
    q["connected_components"] = (q_components, SQL_COMPONENTS)
    q["spectrum_fixture"] = (q_spectrum, SQL_SPECTRUM)
    q["topology_degrees"] = (q_topology_degrees, SQL_TOPOLOGY_DEGREES)
    q["topology_sweep"] = (q_topology_sweep, None)
    q["topology_trend"] = (q_topology_trend, SQL_TOPOLOGY_TREND)
    q["mask_values"] = (q_mask_values, f"select party, comp, t, round(delta, 9) as delta from ({_DRAWS})")
    q["mask_telescopes"] = (q_mask_telescopes, SQL_TELESCOPES)
    q["mask_gap"] = (q_mask_gap, SQL_MASK_GAP)
    for kind in consensus.KINDS:
        q[f"consensus_{kind}_total"] = (partial(q_total, kind), SQL_TOTAL)
        q[f"consensus_{kind}_trace"] = (partial(q_trace, kind), sql_trace(kind))
    for engine in ("array", "edge", "closed", "driver"):
        q[f"consensus_engine_{engine}"] = (lambda s, d, e=engine: q_total("masked_boosted", s, d, e, 60), SQL_TOTAL)
    q["consensus_two_term_trace"] = (partial(q_trace, "masked_boosted", form="two_term"), sql_trace("masked_boosted"))
    q["consensus_error_race"] = (q_error_race, SQL_ERROR_RACE)
    q["rounds_to_eps"] = (q_rounds_to_eps, SQL_ROUNDS_TO_EPS)
    q["shared_by_first_party"] = (q_shared_by_first, SQL_SHARED_BY_FIRST)
    q["party_disagreement"] = (q_disagreement, SQL_DISAGREEMENT)
    q["messages_sent"] = (q_messages, SQL_MESSAGES)
    q["direct_sum"] = (q_direct_sum, SQL_DIRECT)
    q["secure_shares_total"] = (q_secure_shares, SQL_SHARES)
    q["assign_hard"] = (q_assign, SQL_ASSIGN)
    q["membership_fuzzy"] = (partial(q_soft, "fuzzy"), SQL_SOFT_FUZZY)
    q["responsibility_gmm"] = (partial(q_soft, "gmm"), SQL_SOFT_GMM)
    q["local_summary"] = (q_local_summary, SQL_LOCAL)
    for what, sql in SQL_DISCLOSE.items():
        q[f"disclose_{what}"] = (partial(q_disclose, what), sql)
    for how in ("exact", "squared"):
        q[f"silhouette_{how}"] = (partial(q_silhouette, how), sql_silhouette(how))
    q["silhouette_by_k"] = (q_silhouette_by_k, _silhouette_by_k_sql())
    q["sse_archetypes"] = (q_sse, SQL_SSE)
    q["sse_by_k"] = (q_sse_by_k, None)
    q["missed_patterns"] = (q_missed_patterns, SQL_MISSED)
    for kind in ("central", "masked"):
        q[f"union_patterns_{kind}"] = (partial(q_union_patterns, kind == "masked"), SQL_UNION_PATTERNS)
    q["cluster_sizes"] = (q_cluster_sizes, SQL_SIZES)
    q["centroid_gap"] = (q_centroid_gap, SQL_CENTROID_GAP)
    q["assignment_parity"] = (q_parity, SQL_PARITY)
    q["family_objectives"] = (q_objectives, SQL_OBJECTIVES)
    q["family_times"] = (q_times, None)
    q["iteration_parity"] = (q_iteration_parity, SQL_ITERATION_PARITY)
    q["payload_cost"] = (q_payload_cost, SQL_PAYLOAD)
    q["upload_cost"] = (q_upload_cost, SQL_UPLOAD)
    q["upload_measured"] = (q_upload_measured, None)
    q["multiplication_cost"] = (q_multiplications, SQL_MULTIPLICATIONS)
    q["privacy_audit"] = (q_audit, None)
    q["embedding_parties"] = (q_embedding_parties, SQL_EMBEDDING_PARTIES)
    q["nation_parties"] = (q_nation_parties, SQL_NATION_PARTIES)
    q["nation_kmeans"] = (q_nation_kmeans, SQL_NATION_KMEANS)
    q["text_features"] = (q_text_features, SQL_TEXT_FEATURES)
    return q
