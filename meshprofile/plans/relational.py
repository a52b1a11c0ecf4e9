"""Surrounding operators: one small query each, with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from meshprofile.functions import udfs
from meshprofile.operators import relational as rel
from meshprofile.operators import topology
from meshprofile.plans import duck
from meshprofile.sources import graphs, io
from meshprofile.sources.tables import slot_of, table

SLOT_SQL = "((hour(ts) * 60 + minute(ts)) // 30)::bigint"
Q: dict[str, tuple] = {}


def query(name: str, sql: str | None):
    def register(fn):
        Q[name] = (fn, sql)
        return fn

    return register


def events(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").select("event_id", "ts", "user_id", "event_type", "value", "props")


def slotted(s: SparkSession, d: str) -> DataFrame:
    return events(s, d).withColumn("slot", slot_of("ts").cast("long"))


def both(names: list[str], sql: str, make) -> None:
    """The same query under several names: a join by each physical strategy, for example."""
    for n in names:
        Q[n] = ((lambda s, d, n=n: make(s, d, n)), sql)


# scans, round trips, sinks ----------------------------------------------------------------------------


@query("scan_parquet", "select event_id, user_id, round(value, 4) as value from events")
def scan_parquet(s, d):
    return s.read.schema("event_id long, user_id long, value double").parquet(f"{d}/events.parquet").select("event_id", "user_id", F.round("value", 4).alias("value"))


@query("scan_projected", "select user_id, count(*) as n from events group by user_id")
def scan_projected(s, d):
    return table(s, d, "events").groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query("scan_filtered", "select event_id, user_id from events where user_id < 100 and event_type = 'purchase'")
def scan_filtered(s, d):
    return table(s, d, "events").where((F.col("user_id") < 100) & (F.col("event_type") == "purchase")).select("event_id", "user_id")


DAY_USER = "select user_id, count(*) as n, round(sum(value), 4) as v from events group by user_id"


def day_user(s, d):
    return events(s, d).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("v"))


for kind in ("csv", "json", "orc"):
    Q[f"roundtrip_{kind}"] = ((lambda s, d, k=kind: io.round_trip(day_user(s, d), k)), DAY_USER)
Q["sink_partitioned"] = (lambda s, d: io.partitioned(day_user(s, d).withColumn("party", F.pmod("user_id", F.lit(10))), "party"), "select user_id % 10 as party, user_id, count(*) as n, round(sum(value), 4) as v from events group by user_id")


@query("sink_replaced", "select user_id % 10 as party, user_id, case when user_id % 10 < 5 then count(*) else -1 end as n from events group by user_id")
def sink_replaced(s, d):
    """Dynamic partition overwrite: parties 0..4 anew over a table in which all parties are stale."""
    own = day_user(s, d).select(F.pmod("user_id", F.lit(10)).alias("party"), "user_id", "n")
    return io.replaced(own.where("party < 5"), "party", own.withColumn("n", F.lit(-1).cast("long")))


Q["sink_bucketed"] = (lambda s, d: io.bucketed(day_user(s, d), "user_id", 8), DAY_USER)


@query("source_graph", "select i as src, j as dst from (select r.i, (r.i + 1) % 10 as j from range(10) r(i) union select (r.i + 1) % 10, r.i from range(10) r(i))")
def source_graph(s, d):
    graphs.register(s)
    return s.read.format("topology").option("kind", "ring").option("n", "10").load().select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))


# projections and filters ------------------------------------------------------------------------------


@query("proj_computed", f"select event_id, {SLOT_SQL} as slot, user_id % 10 as party, round(value * 2 + 1, 4) as v from events")
def proj_computed(s, d):
    return slotted(s, d).select("event_id", "slot", F.pmod("user_id", F.lit(10)).alias("party"), F.round(F.col("value") * 2 + 1, 4).alias("v"))


@query("proj_struct", "select event_id, user_id as u, event_type as kind from events")
def proj_struct(s, d):
    return events(s, d).select("event_id", F.struct(F.col("user_id").alias("u"), F.col("event_type").alias("kind")).alias("who")).select("event_id", "who.u", "who.kind")


@query("proj_case", "select event_id, case when hour(ts) < 7 then 'night' when hour(ts) between 17 and 20 then 'peak' else 'day' end as band from events")
def proj_case(s, d):
    return events(s, d).select("event_id", F.when(F.hour("ts") < 7, "night").when(F.hour("ts").between(17, 20), "peak").otherwise("day").alias("band"))


@query("filter_range", "select event_id from events where value between 10 and 20")
def filter_range(s, d):
    return events(s, d).where(F.col("value").between(10, 20)).select("event_id")


@query("filter_in", "select event_id from events where event_type in ('click', 'purchase')")
def filter_in(s, d):
    return events(s, d).where(F.col("event_type").isin("click", "purchase")).select("event_id")


@query("filter_like", "select c_custkey from customer where c_name like '%1' or regexp_matches(c_mktsegment, '^(AUTO|MACH)')")
def filter_like(s, d):
    return table(s, d, "customer").where(F.col("c_name").like("%1") | F.col("c_mktsegment").rlike("^(AUTO|MACH)")).select("c_custkey")


@query("filter_null", "select count(*) as n from events where value is not null and event_type is not null")
def filter_null(s, d):
    return events(s, d).where(F.col("value").isNotNull() & F.col("event_type").isNotNull()).agg(F.count(F.lit(1)).alias("n"))


@query("filter_array", "select user_id from (select user_id, sum(value) as v from events group by user_id, hour(ts)) group by user_id having max(v) > 400 and min(v) > 0")
def filter_array(s, d):
    per = events(s, d).groupBy("user_id", F.hour("ts").alias("h")).agg(F.sum("value").alias("v")).groupBy("user_id").agg(F.collect_list("v").alias("y"))
    return per.where(F.exists("y", lambda v: v > 400) & F.forall("y", lambda v: v > 0)).select("user_id")


# joins ------------------------------------------------------------------------------------------------

STAR = "select r_name, n_name, count(*) as n from events join customer on c_custkey = user_id join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by all"


def star(s, d, name):
    hint = {"join_broadcast": "broadcast", "join_sortmerge": "merge", "join_shufflehash": "shuffle_hash"}[name]
    c = table(s, d, "customer").select("c_custkey", "c_nationkey").hint(hint)
    n, r = table(s, d, "nation"), table(s, d, "region")
    e = events(s, d).select("user_id")
    joined = e.join(c, e.user_id == c.c_custkey).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


both(["join_broadcast", "join_sortmerge", "join_shufflehash"], STAR, star)


@query("join_left", "select u.user_id, s.slot, coalesce(sum(e.value), 0) > 0 as used from (select distinct user_id from events) u cross join range(48) s(slot) left join events e on e.user_id = u.user_id and (hour(e.ts) * 60 + minute(e.ts)) // 30 = s.slot group by all")
def join_left(s, d):
    e = slotted(s, d)
    grid = e.select("user_id").distinct().withColumn("slot", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(47).cast("long"))))
    return grid.join(e, ["user_id", "slot"], "left").groupBy("user_id", "slot").agg((F.coalesce(F.sum("value"), F.lit(0.0)) > 0).alias("used"))


@query("join_right", "select c_custkey, count(event_id) as n from events right join customer on c_custkey = user_id group by c_custkey")
def join_right(s, d):
    return events(s, d).join(table(s, d, "customer").select("c_custkey"), F.col("user_id") == F.col("c_custkey"), "right").groupBy("c_custkey").agg(F.count("event_id").alias("n"))


@query("join_full", "select coalesce(a.user_id, b.user_id) as user_id, a.n as clicks, b.n as buys from (select user_id, count(*) as n from events where event_type = 'click' group by 1) a full join (select user_id, count(*) as n from events where event_type = 'purchase' group by 1) b on a.user_id = b.user_id")
def join_full(s, d):
    def per(kind, name):
        return events(s, d).where(F.col("event_type") == kind).groupBy("user_id").agg(F.count(F.lit(1)).alias(name))

    return per("click", "clicks").join(per("purchase", "buys"), "user_id", "full").select("user_id", F.coalesce("clicks", F.lit(None).cast("long")).alias("clicks"), "buys")


@query("join_semi", "select c_custkey from customer where c_custkey in (select user_id from events)")
def join_semi(s, d):
    return table(s, d, "customer").select("c_custkey").join(events(s, d), F.col("c_custkey") == F.col("user_id"), "left_semi")


@query("join_anti", "select c_custkey from customer where c_custkey not in (select user_id from events)")
def join_anti(s, d):
    return table(s, d, "customer").select("c_custkey").join(events(s, d), F.col("c_custkey") == F.col("user_id"), "left_anti")


@query("join_cross", "select n_nationkey, r_regionkey, n_regionkey = r_regionkey as own from nation, region")
def join_cross(s, d):
    return table(s, d, "nation").crossJoin(F.broadcast(table(s, d, "region"))).select("n_nationkey", "r_regionkey", (F.col("n_regionkey") == F.col("r_regionkey")).alias("own"))


@query("join_theta", "select a.n_nationkey as a, b.n_nationkey as b from nation a join nation b on a.n_nationkey < b.n_nationkey and a.n_regionkey = b.n_regionkey")
def join_theta(s, d):
    n = table(s, d, "nation").select("n_nationkey", "n_regionkey")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, F.expr("a.n_nationkey < b.n_nationkey and a.n_regionkey = b.n_regionkey")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b"))


OUTAGES = [(i, f"2024-01-{3 * i + 1:02d} 02:00:00", f"2024-01-{3 * i + 1:02d} 09:30:00") for i in range(9)]
OUTAGES_SQL = "(values " + ", ".join(f"({i}, timestamp '{a}', timestamp '{b}')" for i, a, b in OUTAGES) + ") o(id, a, b)"


@query("join_range", f"select o.id::bigint as outage, count(*) as n from events join {OUTAGES_SQL} on ts >= o.a and ts < o.b group by all")
def join_range(s, d):
    outages = s.createDataFrame(OUTAGES, "id long, a string, b string").select("id", F.col("a").cast("timestamp_ntz").alias("a"), F.col("b").cast("timestamp_ntz").alias("b"))
    return rel.range_join(events(s, d), outages, "ts", "a", "b", bin_seconds=3600).groupBy(F.col("id").alias("outage")).agg(F.count(F.lit(1)).alias("n"))


@query("join_interval", "select c.event_id as click, p.event_id as buy from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 6 hour")
def join_interval(s, d):
    e = events(s, d).select("event_id", "user_id", "ts", "event_type")
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("buy"), "user_id", F.col("ts").alias("t1"))
    return rel.interval_join(c, p, "user_id", "t0", "t1", 6 * 3600).select("click", "buy")


@query("join_asof", "select p.event_id, (select round(arg_max(e.value, e.ts), 4) from events e where e.user_id = p.user_id and e.event_type = 'signup' and e.ts <= p.ts) as v from events p where p.event_type = 'purchase'")
def join_asof(s, d):
    e = events(s, d)
    left, right = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'signup'").select("user_id", "ts", "value")
    return rel.as_of_join(left, right, "user_id", "ts", "value").select("event_id", F.round("value", 4).alias("v"))


GRAPH = sorted(set(graphs.named("unsafe")) | {(0, 5), (3, 7)})
GRAPH_SQL = "e as (select * from (values " + ", ".join(f"({i}, {j})" for a, b in GRAPH for i, j in ((a, b), (b, a))) + ") v(src, dst))"


@query("join_self_neighbours", f"with {GRAPH_SQL}, n as (select src, dst from e union select src, src from e) select e.src::bigint as a, e.dst::bigint as b, (select count(*) from n where n.src = e.dst and n.dst not in (select dst from n m where m.src = e.src)) as unheard from e")
def join_self(s, d):
    """For both ends of every edge, how many of the other's closed neighbours one does not hear."""
    e = graphs.edges_df(s, GRAPH)
    near = e.groupBy("src").agg(F.array_union(F.collect_set("dst"), F.array(F.first("src"))).alias("near"))
    pairs = e.join(near, "src").join(near.select(F.col("src").alias("dst"), F.col("near").alias("near2")), "dst")
    return pairs.select(F.col("src").cast("long").alias("a"), F.col("dst").cast("long").alias("b"), F.size(F.array_except("near2", "near")).cast("long").alias("unheard"))


@query("join_lateral", "select user_id, slot, round(v, 4) as v from (select *, row_number() over (partition by user_id order by v desc, slot) as rn from (select user_id, (hour(ts) * 2 + minute(ts) // 30)::bigint as slot, sum(value) as v from events group by all)) where rn <= 3")
def join_lateral(s, d):
    """A slot's values are added in the order of their ids, so that sums equal but for rounding rank the same in every run."""
    e = slotted(s, d).select("event_id", "user_id", "slot", "value").repartition("user_id")
    upto = Window.partitionBy("user_id", "slot").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    back = Window.partitionBy("user_id", "slot").orderBy("event_id")
    per = e.withColumn("v", F.sum("value").over(upto)).withColumn("last", F.lead(F.lit(False), 1, True).over(back)).where("last")
    # descending, so that nulls come last and NaN first
    tops = per.groupBy("user_id").agg(F.slice(F.sort_array(F.collect_list(F.struct("v", (-F.col("slot")).alias("minus"))), False), 1, 3).alias("t"))
    out = tops.lateralJoin(s.tvf.inline(F.col("t").outer()))
    return out.select("user_id", (-F.col("minus")).alias("slot"), F.round("v", 4).alias("v"))


# aggregates -------------------------------------------------------------------------------------------


@query("agg_hash", "select user_id % 10 as party, event_type, count(*) as n, round(sum(value), 3) as v from events group by all")
def agg_hash(s, d):
    return events(s, d).groupBy(F.pmod("user_id", F.lit(10)).alias("party"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 3).alias("v"))


@query("agg_sort", "select user_id, string_agg(event_id::varchar, ',' order by event_id) as ids from events group by user_id")
def agg_sort(s, d):
    return events(s, d).groupBy("user_id").agg(F.array_join(F.sort_array(F.collect_list("event_id")), ",").alias("ids"))


@query("agg_distinct", f"select {SLOT_SQL} as slot, count(distinct user_id) as users, count(distinct event_type) as kinds from events group by all")
def agg_distinct(s, d):
    return slotted(s, d).groupBy("slot").agg(F.countDistinct("user_id").alias("users"), F.countDistinct("event_type").alias("kinds"))


@query("agg_filter", "select user_id, count(*) filter (event_type = 'click') as clicks, count(*) filter (value > 50) as large from events group by all")
def agg_filter(s, d):
    return events(s, d).groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.count_if(F.col("value") > 50).alias("large"))


@query("agg_approx", "select user_id % 10 as party, count(distinct user_id) as users, round(median(value), 4) as mid, true as users_near, true as median_near from events group by all")
def agg_approx(s, d):
    """Exact figures, and whether the approximate ones are within their error."""
    e = events(s, d).withColumn("party", F.pmod("user_id", F.lit(10)))
    got = e.groupBy("party").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.countDistinct("user_id").alias("n"), F.percentile_approx("value", 0.5, 1000).alias("p"), F.median("value").alias("m"))
    return got.select("party", F.col("n").alias("users"), F.round("m", 4).alias("mid"), (F.abs(F.col("a") - F.col("n")) <= 0.1 * F.col("n")).alias("users_near"), (F.abs(F.col("p") - F.col("m")) <= 5).alias("median_near"))


@query(
    "agg_stats",
    """select event_type, round(avg(value), 4) as mean, round(stddev_samp(value), 4) as sd, round(var_pop(value), 3) as var, round(corr(value, user_id), 6) as r, round(covar_pop(value, user_id), 3) as cov, round(median(value), 4) as med, arg_max(event_id, value) as top, arg_min(event_id, value) as low,
round((avg(value ^ 3) - 3 * avg(value) * avg(value ^ 2) + 2 * avg(value) ^ 3) / stddev_pop(value) ^ 3, 4) as skew, round((avg(value ^ 4) - 4 * avg(value) * avg(value ^ 3) + 6 * avg(value) ^ 2 * avg(value ^ 2) - 3 * avg(value) ^ 4) / var_pop(value) ^ 2 - 3, 3) as kurt,
(select h from (select event_type as t, hour(ts)::bigint as h, count(*) as n from events group by all) c where c.t = e.event_type order by n desc, h limit 1) as busiest from events e group by event_type""",
)
def agg_stats(s, d):
    """Of several events with the extreme value, top and low name the one with the smallest id, the first in the table."""
    e = events(s, d).withColumn("h", F.hour("ts").cast("long"))
    there = F.col("value").isNotNull() & F.col("event_id").isNotNull()
    return e.groupBy("event_type").agg(
        F.round(F.avg("value"), 4).alias("mean"),
        F.round(F.stddev_samp("value"), 4).alias("sd"),
        F.round(F.var_pop("value"), 3).alias("var"),
        F.round(F.corr("value", "user_id"), 6).alias("r"),
        F.round(F.covar_pop("value", "user_id"), 3).alias("cov"),
        F.round(F.median("value"), 4).alias("med"),
        F.max_by("event_id", F.when(there, F.struct("value", -F.col("event_id")))).alias("top"),
        F.min_by("event_id", F.when(there, F.struct("value", "event_id"))).alias("low"),
        F.round(F.skewness("value"), 4).alias("skew"),
        F.round(F.kurtosis("value"), 3).alias("kurt"),
        F.mode("h", True).alias("busiest"),
    )


ROLL = "from (select r_name, n_name, c_acctbal from customer join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey)"


def rolled(s, d):
    c = table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return c.select("r_name", "n_name", "c_acctbal")


@query("agg_rollup", f"select r_name, n_name, count(*) as n {ROLL} group by rollup (r_name, n_name)")
def agg_rollup(s, d):
    return rolled(s, d).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query("agg_cube", f"select r_name, n_name, count(*) as n {ROLL} group by cube (r_name, n_name)")
def agg_cube(s, d):
    return rolled(s, d).cube("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@query("agg_grouping_sets", f"select r_name, n_name, grouping(r_name)::bigint as g, count(*) as n {ROLL} group by grouping sets ((r_name), (n_name))")
def agg_grouping_sets(s, d):
    return rolled(s, d).groupingSets([["r_name"], ["n_name"]], "r_name", "n_name").agg(F.grouping("r_name").cast("long").alias("g"), F.count(F.lit(1)).alias("n"))


@query("agg_pivot", "select user_id, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase from events group by all")
def agg_pivot(s, d):
    return events(s, d).groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1))).na.fill(0, ["click", "purchase"])


@query("agg_unpivot", "select c_custkey, 'c_nationkey' as what, c_nationkey::double as v from customer union all select c_custkey, 'c_acctbal', c_acctbal::double from customer")
def agg_unpivot(s, d):
    c = table(s, d, "customer").select("c_custkey", F.col("c_nationkey").cast("double").alias("c_nationkey"), F.col("c_acctbal").cast("double").alias("c_acctbal"))
    return c.unpivot("c_custkey", ["c_nationkey", "c_acctbal"], "what", "v")


@query("agg_vector_sum", "select label, i::bigint as i, round(sum(v::double), 4) as v from (select label, unnest(embedding) as v, generate_subscripts(embedding, 1) - 1 as i from embeddings) group by all")
def agg_vector_sum(s, d):
    long = table(s, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "v"))
    return long.groupBy("label", F.col("i").cast("long").alias("i")).agg(F.round(F.sum(F.col("v").cast("double")), 4).alias("v"))


# windows and order ------------------------------------------------------------------------------------

PER_USER = "(select user_id, user_id % 10 as party, round(sum(value), 4) as v from events group by user_id) t"


def per_user(s, d):
    return events(s, d).groupBy("user_id").agg(F.round(F.sum("value"), 4).alias("v")).withColumn("party", F.pmod("user_id", F.lit(10)))


def ranking(name: str):
    made = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "ntile": lambda: F.ntile(4), "percent_rank": F.percent_rank, "cume_dist": F.cume_dist}[name]

    def run(s, d):
        col = made().over(Window.partitionBy("party").orderBy(F.desc("v"), "user_id"))
        col = F.round(col, 6) if name in ("percent_rank", "cume_dist") else col.cast("long")
        return per_user(s, d).select("user_id", "party", col.alias("r"))

    return run


for name in ("row_number", "rank", "dense_rank", "ntile", "percent_rank", "cume_dist"):
    call = f"{name}({4 if name == 'ntile' else ''}) over (partition by party order by v desc, user_id)"
    Q[f"win_{name}"] = (ranking(name), f"select user_id, party, {f'round({call}, 6)' if name in ('percent_rank', 'cume_dist') else call + '::bigint'} as r from {PER_USER}")

HOURS = "(select user_id, hour(ts)::bigint as h, round(sum(value), 4) as v from events group by all) t"


def hours(s, d):
    return events(s, d).groupBy("user_id", F.hour("ts").cast("long").alias("h")).agg(F.round(F.sum("value"), 4).alias("v"))


@query("win_lag_lead", f"select user_id, h, round(v - lag(v, 1, 0.0) over w, 4) as up, round(lead(v, 1, 0.0) over w - v, 4) as next from {HOURS} window w as (partition by user_id order by h)")
def win_lag_lead(s, d):
    w = Window.partitionBy("user_id").orderBy("h")
    return hours(s, d).select("user_id", "h", F.round(F.col("v") - F.lag("v", 1, 0.0).over(w), 4).alias("up"), F.round(F.lead("v", 1, 0.0).over(w) - F.col("v"), 4).alias("next"))


FULL = "(partition by user_id order by h rows between unbounded preceding and unbounded following)"


@query("win_first_last", f"select user_id, h, first_value(v) over w as f, last_value(v) over w as l from {HOURS} window w as {FULL}")
def win_first_last(s, d):
    w = Window.partitionBy("user_id").orderBy("h").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return hours(s, d).select("user_id", "h", F.first("v").over(w).alias("f"), F.last("v").over(w).alias("l"))


@query("win_nth", f"select user_id, h, nth_value(v, 2) over w as second from {HOURS} window w as {FULL}")
def win_nth(s, d):
    w = Window.partitionBy("user_id").orderBy("h").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return hours(s, d).select("user_id", "h", F.nth_value("v", 2).over(w).alias("second"))


@query("win_running_rows", f"select user_id, h, round(sum(v) over (partition by user_id order by h rows unbounded preceding), 3) as run from {HOURS}")
def win_running(s, d):
    return hours(s, d).select("user_id", "h", F.round(F.sum("v").over(Window.partitionBy("user_id").orderBy("h").rowsBetween(Window.unboundedPreceding, 0)), 3).alias("run"))


@query("win_moving_rows", f"select user_id, h, round(avg(v) over (partition by user_id order by h rows between 2 preceding and current row), 3) as mean3 from {HOURS}")
def win_moving(s, d):
    return hours(s, d).select("user_id", "h", F.round(F.avg("v").over(Window.partitionBy("user_id").orderBy("h").rowsBetween(-2, 0)), 3).alias("mean3"))


@query("win_range_frame", "select event_id, round(sum(value) over (partition by user_id order by floor(epoch(ts))::bigint range between 86400 preceding and current row), 3) as day from events")
def win_range(s, d):
    w = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    e = events(s, d).withColumn("sec", F.unix_timestamp(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.round(F.sum("value").over(w), 3).alias("day"))


@query("sort_global", "select event_id, round(value, 4) as value from events order by value desc, event_id")
def sort_global(s, d):
    return events(s, d).orderBy(F.desc("value"), "event_id").select("event_id", F.round("value", 4).alias("value"))


@query("sort_within", "select user_id, event_id from events")
def sort_within(s, d):
    return events(s, d).repartition("user_id").sortWithinPartitions("user_id", "ts").select("user_id", "event_id")


@query("limit_topk", "select event_id, round(value, 4) as value from events order by events.value desc, event_id limit 20")
def limit_topk(s, d):
    return events(s, d).orderBy(F.desc("value"), "event_id").limit(20).select("event_id", F.round("value", 4).alias("value"))


@query("topk_per_group", f"select user_id, party, v from (select *, row_number() over (partition by party order by v desc, user_id) as rn from {PER_USER}) where rn <= 2")
def topk_per_group(s, d):
    ranked = per_user(s, d).withColumn("rn", F.row_number().over(Window.partitionBy("party").orderBy(F.desc("v"), "user_id")))
    return ranked.where("rn <= 2").select("user_id", "party", "v")


@query("offset_page", f"select user_id, v from {PER_USER} order by user_id limit 20 offset 40")
def offset_page(s, d):
    return per_user(s, d).orderBy("user_id").offset(40).limit(20).select("user_id", "v")


# sets -------------------------------------------------------------------------------------------------

A, B = "(select user_id, event_type from events where event_type in ('click', 'purchase'))", "(select user_id, event_type from events where value > 60)"
for name, op, call in (("union", "union all", "union"), ("intersect", "intersect", "intersect"), ("intersect_all", "intersect all", "intersectAll"), ("except", "except", "subtract"), ("except_all", "except all", "exceptAll")):

    def set_op(s, d, call=call):
        e = events(s, d)
        a = e.where(F.col("event_type").isin("click", "purchase")).select("user_id", "event_type")
        return getattr(a, call)(e.where("value > 60").select("user_id", "event_type"))

    Q[f"set_{name}"] = (set_op, f"select * from {A} {op} select * from {B}")


@query("set_union_by_name", f"select user_id, event_type from {A} union all select user_id, event_type from {B}")
def set_union_by_name(s, d):
    e = events(s, d)
    return e.where(F.col("event_type").isin("click", "purchase")).select("user_id", "event_type").unionByName(e.where("value > 60").select("event_type", "user_id"))


# functions --------------------------------------------------------------------------------------------


@query("fn_string", "select c_custkey, upper(c_name) as up, substr(c_name, 1, 4) as head, concat_ws('-', c_name, c_mktsegment) as both, split_part(c_name, '#', 2) as tail, regexp_extract(c_name, '([0-9]+)', 1) as digits, regexp_replace(c_name, '0+', '', 'g') as bare, lpad(c_custkey::varchar, 8, '0') as padded, sha256(c_name) as hash, length(c_name)::bigint as len from customer")
def fn_string(s, d):
    return table(s, d, "customer").select("c_custkey", F.upper("c_name").alias("up"), F.substring("c_name", 1, 4).alias("head"), F.concat_ws("-", "c_name", "c_mktsegment").alias("both"), F.coalesce(F.split_part("c_name", F.lit("#"), F.lit(2)), F.lit("")).alias("tail"), F.regexp_extract("c_name", "([0-9]+)", 1).alias("digits"), F.regexp_replace("c_name", "0+", "").alias("bare"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.sha2("c_name", 256).alias("hash"), F.length("c_name").cast("long").alias("len"))


@query("fn_date", "select event_id, hour(ts) as h, minute(ts) as m, dayofweek(ts) + 1 as dow, strftime(date_trunc('day', ts), '%Y-%m-%d') as day, strftime(ts::date + 7, '%Y-%m-%d') as later, date_diff('day', date '2024-01-01', ts::date) as days, floor(epoch(ts))::bigint as sec, floor(epoch(ts + interval 1 month + interval 2 hour))::bigint as due from events")
def fn_date(s, d):
    ts = F.col("ts")
    due = ts.cast("timestamp") + F.make_interval(months=F.lit(1), hours=F.lit(2))
    return events(s, d).select("event_id", F.hour(ts).cast("long").alias("h"), F.minute(ts).cast("long").alias("m"), F.dayofweek(ts).cast("long").alias("dow"), F.date_format(F.date_trunc("day", ts.cast("timestamp")), "yyyy-MM-dd").alias("day"), F.date_format(F.date_add(F.to_date(ts), 7), "yyyy-MM-dd").alias("later"), F.datediff(F.to_date(ts), F.lit("2024-01-01")).cast("long").alias("days"), F.unix_timestamp(ts.cast("timestamp")).alias("sec"), F.unix_timestamp(due).alias("due"))


@query("fn_math", "select event_id, round(pow(value, 2), 2) as p, round(ln(value + 1), 6) as l, round(exp(-value / 100), 6) as e, abs(event_id - 500) as b, round(sqrt(value), 6) as q, floor(value)::bigint as f, round(greatest(value, 50), 4) as g, round(least(value, 50), 4) as s, event_id % 7 as r, upper(to_hex(event_id)) as x, (case when value < 0 then 0 when value >= 200 then 11 else floor(value / 20) + 1 end)::bigint as bucket from events")
def fn_math(s, d):
    v = F.col("value")
    return events(s, d).select("event_id", F.round(F.pow(v, F.lit(2)), 2).alias("p"), F.round(F.log(v + 1), 6).alias("l"), F.round(F.exp(-v / 100), 6).alias("e"), F.abs(F.col("event_id") - 500).alias("b"), F.round(F.sqrt(v), 6).alias("q"), F.floor(v).alias("f"), F.round(F.greatest(v, F.lit(50.0)), 4).alias("g"), F.round(F.least(v, F.lit(50.0)), 4).alias("s"), F.pmod("event_id", F.lit(7)).alias("r"), F.conv(F.col("event_id").cast("string"), 10, 16).alias("x"), F.width_bucket(v, F.lit(0.0), F.lit(200.0), F.lit(10).cast("long")).alias("bucket"))


@query(
    "fn_array",
    """select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as sq, round(list_max(embedding)::double, 5) as top, (list_position(embedding, list_max(embedding)) - 1)::bigint as at, len(list_filter(embedding, lambda x: x > 0))::bigint as pos,
round(list_sum(list_transform(range(1, 64), lambda i: (embedding[i]::double - embedding[i + 1]::double) ^ 2)), 4) as steps, len(list_filter(embedding, lambda x: x > 0.4)) > 0 as peak, round(list_sum(embedding[1:8])::double, 4) as head, round(list_sum([x::double for x in list_sort(embedding)][1:3]), 4) as least,
round(list_sum(embedding[1:8])::double + list_sum(embedding[57:64])::double, 4) as ends, round(list_sum(list_transform(range(1, 65), lambda i: (i - 1) * embedding[i]::double)), 3) as ramp, (64 - len(list_distinct(list_filter(embedding, lambda x: x > 0))))::bigint as rest from embeddings""",
)
def fn_array(s, d):
    e, y = table(s, d, "embeddings").withColumn("y", F.transform("embedding", lambda x: x.cast("double"))), F.col("y")
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda p, q: p + q)
    place = F.sequence(F.lit(0), F.size(y) - 1)
    return e.select(
        "vec_id",
        F.round(F.aggregate(y, F.lit(0.0), lambda a, x: a + x * x), 4).alias("sq"),
        F.round(F.array_max("embedding").cast("double"), 5).alias("top"),
        (F.array_position("embedding", F.array_max("embedding")) - 1).alias("at"),
        F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("pos"),
        F.round(total(F.zip_with(F.slice(y, 1, 63), F.slice(y, 2, 63), lambda a, b: (a - b) * (a - b))), 4).alias("steps"),
        F.exists("embedding", lambda x: x > 0.4).alias("peak"),
        F.round(total(F.slice(y, 1, 8)), 4).alias("head"),
        F.round(total(F.slice(F.array_sort(y), 1, 3)), 4).alias("least"),
        F.round(total(F.flatten(F.array(F.slice(y, 1, 8), F.slice(y, 57, 8)))), 4).alias("ends"),
        F.round(total(F.transform(F.arrays_zip(place.alias("i"), y.alias("v")), lambda c: c["i"] * c["v"])), 3).alias("ramp"),
        (F.lit(64) - F.size(F.array_except(y, F.filter(y, lambda x: x <= 0)))).cast("long").alias("rest"),
    )


@query(
    "fn_map",
    """with h as (select user_id, hour(ts) as h, round(sum(value), 4) as v, count(*) as n from events group by all)
select user_id, count(*) as used, round(max(v), 4) as top, round(sum(v * n), 4) as weighed, round(coalesce(max(v) filter (h = 12), 0), 4) as noon, round(sum(2 * v), 4) as twice from h where v > 100 group by user_id""",
)
def fn_map(s, d):
    per = events(s, d).groupBy("user_id", F.hour("ts").cast("long").alias("h")).agg(F.round(F.sum("value"), 4).alias("v"), F.count(F.lit(1)).alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("h", "v"))).alias("m"), F.map_from_entries(F.collect_list(F.struct("h", "n"))).alias("c"))
    m = m.withColumn("m", F.map_filter("m", lambda k, v: v > 100)).where(F.size("m") > 0)
    weighed = F.map_zip_with("m", "c", lambda k, v, n: v * n)
    total = lambda x: F.aggregate(F.map_values(x), F.lit(0.0), lambda a, v: a + F.coalesce(v, F.lit(0.0)))
    return m.select(
        "user_id",
        F.size(F.map_keys("m")).cast("long").alias("used"),
        F.round(F.array_max(F.map_values("m")), 4).alias("top"),
        F.round(total(weighed), 4).alias("weighed"),
        F.round(F.coalesce(F.element_at("m", F.lit(12).cast("long")), F.lit(0.0)), 4).alias("noon"),
        F.round(total(F.transform_values("m", lambda k, v: 2 * v)), 4).alias("twice"),
    )


@query("fn_json", "select event_id, json_extract(props, '$.k')::bigint as k, json_extract_string(props, '$.k') as t, json_extract_string(props, '$.k') as u, '{\"id\":' || event_id || ',\"kind\":\"' || event_type || '\"}' as doc from events")
def fn_json(s, d):
    e = events(s, d)
    e = e.select("event_id", F.from_json("props", "k long")["k"].alias("k"), F.get_json_object("props", "$.k").alias("t"), F.json_tuple("props", "k").alias("u"), "event_type")
    return e.select("event_id", "k", "t", "u", F.to_json(F.struct(F.col("event_id").alias("id"), F.col("event_type").alias("kind"))).alias("doc"))


@query("fn_conditional", "select event_id, coalesce(nullif(event_type, 'click'), 'c') as kind, case when value = 0 then null else round(100 / value, 4) end as inv from events")
def fn_conditional(s, d):
    return events(s, d).select("event_id", F.coalesce(F.nullif("event_type", F.lit("click")), F.lit("c")).alias("kind"), F.round(F.try_divide(F.lit(100), F.col("value")), 4).alias("inv"))


# subqueries -------------------------------------------------------------------------------------------


def sql(s: SparkSession, d: str, text: str) -> DataFrame:
    return s.sql(text, events=table(s, d, "events"), customer=table(s, d, "customer"), nation=table(s, d, "nation"))


SUBS = {
    "sub_scalar": "select event_id from {events} where value > (select 2 * avg(value) from {events})",
    "sub_exists": "select c_custkey from {customer} c where exists (select 1 from {events} e where e.user_id = c.c_custkey and e.event_type = 'purchase')",
    "sub_in": "select c_custkey from {customer} where c_custkey in (select user_id from {events} where value > 150)",
    "cte": "with u as (select user_id, count(*) as n from {events} group by user_id) select n, count(*) as users from u group by n",
    "cte_recursive": "with recursive r(party, step) as (select 0, 0 union all select (party + 3) % 10, step + 1 from r where step < 9) select cast(party as bigint) as party, cast(step as bigint) as step from r",
}
for name, text in SUBS.items():
    Q[name] = ((lambda s, d, t=text: sql(s, d, t)), text.replace("{", "").replace("}", ""))


# samples, functions of one's own ----------------------------------------------------------------------


@query("sample_hash", None)
def sample_hash(s, d):
    return events(s, d).where(F.pmod(F.xxhash64("event_id"), F.lit(10)) == 0).select("event_id")


@query("sample_bernoulli", None)
def sample_bernoulli(s, d):
    return events(s, d).sample(0.1, seed=1).select("event_id")


@query("sample_stratified", None)
def sample_stratified(s, d):
    return events(s, d).sampleBy("event_type", {"click": 0.1, "purchase": 0.5}, seed=1).select("event_id", "event_type")


def _udtf_sql(rounds: int = 5) -> str:
    w = topology.boosted_matrix(topology.mixing_matrix(graphs.main_graph()))
    start = f"{duck.peak_profiles(12)},\nstart as (select party, slot as comp, y as x from p where id in (select min(id) from p group by party))"
    states = " union all ".join(f"select {t}::bigint as t, party::bigint as party, comp::bigint as comp, round(x, 6) as x from x{t}" for t in range(rounds + 1))
    return f"with {start},\n{duck.trace('start', w, rounds, 0.0, 0.0)}\n{states}"


NORMS = "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 4) as norm from embeddings"
Q["udf_arrow"] = (lambda s, d: table(s, d, "embeddings").select("vec_id", F.round(udfs.norm_arrow()("embedding"), 4).alias("norm")), NORMS)
Q["udf_pandas"] = (lambda s, d: table(s, d, "embeddings").select("vec_id", F.round(udfs.norm_pandas()("embedding"), 4).alias("norm")), NORMS)
Q["udaf_vector"] = (
    lambda s, d: udfs.vector_totals(table(s, d, "embeddings"), "label", "embedding").select("label", F.posexplode("total").alias("i", "v")).select("label", F.col("i").cast("long").alias("i"), F.round("v", 3).alias("v")),
    "select label, i::bigint as i, round(sum(v::double), 3) as v from (select label, unnest(embedding) as v, generate_subscripts(embedding, 1) - 1 as i from embeddings) group by all",
)
Q["udtf_rounds"] = (udfs.rounds_by_udtf, _udtf_sql())
Q["udf_sql"] = (udfs.sql_functions, "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 4) as q from embeddings")
