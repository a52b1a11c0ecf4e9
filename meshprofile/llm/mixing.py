"""Mixing sources to target weights along a time-varying curriculum.

Every source has a weight schedule over training time 0..1, given by knots and linear in between. The
integral of a source's schedule up to time t, scaled so that the whole of it is the source's target in
words, is its cumulative demand D(t). A source's supply is its documents in hash order, passed over
again when demand exceeds one pass; a copy whose words begin at c in that supply is taken if its
middle lies below the target, and its training position is the time t at which D(t) = c. Sorting by
position (a range sort over all sources) gives the training order.

Supplies are prefix sums in two levels: hash ranges of about BUCKET rows, then rows within a range, so
a source with a third of all rows is never sorted in one task. A source's large documents (over 1/LARGE
of its words, so under LARGE of them) are fitted into the last, partial pass first, greedily by size;
those that do not fit end the supply, so the last document taken is a small part of the source.

Nulls and odd input: null text has size 0; the null source is a source of its own, ranked last; a null
doc_id is placed by its text's hash; repeated rows each count; a source of no words has target 0, and
its documents are taken once if its demand is above zero, else not at all; columns named like the
added ones are replaced.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.llm.common import materialise, table, words_of

BUCKET, LARGE = 4096, 200
WEIGHTS = (5.0, 2.0, 1.0)
SHARE, MOST = 1.5, 2.0
#: Knots (time, relative weight) of the schedules, repeating like WEIGHTS: fading, level, rising.
SCHEDULES = (((0.0, 1.5), (1.0, 0.5)), ((0.0, 1.0), (1.0, 1.0)), ((0.0, 0.5), (1.0, 1.5)))
ADDED = ("size", "source_size", "target", "copies", "taken", "positions")


def share_targets(sizes: list[int], weights: list[float], total: float, most: float = MOST) -> list[float]:
    """total shared by weight; no target above most times its size, the excess shared again by weight until none is."""
    open_, targets, left = [i for i, s in enumerate(sizes) if s > 0], [0.0] * len(sizes), total
    while open_:
        w = sum(weights[i] for i in open_)
        over = [i for i in open_ if left * weights[i] / w > most * sizes[i]]
        for i in over or open_:
            targets[i] = most * sizes[i] if over else left * weights[i] / w
        if not over:
            break
        left -= sum(targets[i] for i in over)
        open_ = [i for i in open_ if i not in over]
    return targets


def choose_large(large: list[tuple[str | None, int, int]], left: dict[str | None, float]) -> dict[str | None, list[int]]:
    """Source -> hashes of its large documents that fit, largest first, into what its last pass still takes."""
    out: dict[str | None, list[int]] = {}
    left = dict(left)
    for source, size, code in sorted(large, key=lambda r: (-r[1], r[2])):
        if size <= left[source]:
            left[source] -= size
            out.setdefault(source, []).append(code)
    return out


def demand_pieces(knots: tuple[tuple[float, float], ...]) -> list[tuple[float, float, float, float, float]]:
    """Per linear piece of a schedule: demand share before it, its start, its weight there, its slope, its length; shares end at 1."""
    area = [(b[0] - a[0]) * (a[1] + b[1]) / 2 for a, b in zip(knots, knots[1:])]
    whole, done, out = sum(area), 0.0, []
    for (t, w), (u, v), part in zip(knots, knots[1:], area):
        out.append((done, t, w / whole, (v - w) / (u - t) / whole, u - t))
        done += part / whole
    return out


def position(share: str, pieces: list[tuple[float, float, float, float, float]]) -> str:
    """SQL for the time at which the demand share is reached: a quadratic inverted piece by piece."""
    sql = "0D"
    for before, start, weight, slope, length in pieces:
        need = f"greatest({share} - {before!r}D, 0D)"
        step = f"2 * {need} / ({weight!r}D + sqrt(greatest({weight!r}D * {weight!r}D + 2 * {slope!r}D * {need}, 0D)) + 1e-300)"
        sql = f"if({share} >= {before!r}D, {start!r}D + least({step}, {length!r}D), {sql})"
    return sql


def mix(docs: DataFrame, weights=WEIGHTS, schedules=SCHEDULES, share: float = SHARE, most: float = MOST, seed: int = 11) -> DataFrame:
    """docs plus size, source_size, target, copies (0 or more), taken and positions (one per copy taken).

    The sources' totals, one row each, are collected to share targets: their number must fit the driver."""
    added = [c for c in docs.columns if c in ADDED or c.startswith("_m")]
    sized = docs.drop(*added).withColumn("size", F.size(words_of(F.col("text"))).cast("long"))
    code = F.sha2(F.concat_ws(":", F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.sha2("text", 256), F.lit(""))), 256)
    sized = sized.withColumn("_mh", F.conv(F.substring(code, 1, 15), 16, 10).cast("long"))  # 60 bits that any SQL can recompute
    slim = materialise(sized.select("source", "size", "_mh"), "mix-sizes")
    totals = sorted(((r["source"], r["s"], r["n"]) for r in slim.groupBy("source").agg(F.sum("size").alias("s"), F.count(F.lit(1)).alias("n")).collect()), key=lambda r: (r[0] is None, r[0] or ""))
    own = [weights[i % len(weights)] for i in range(len(totals))]
    targets = share_targets([s for _, s, _ in totals], own, share * sum(s for _, s, _ in totals), most)
    spark = docs.sparkSession
    plan = [(k, i, int(s), float(t), max(1, -(-n // BUCKET)), i % len(schedules)) for i, ((k, s, n), t) in enumerate(zip(totals, targets))]
    about = spark.createDataFrame(plan, "_mk string, _mn int, source_size long, target double, _mb long, _mc int")
    large = slim.join(F.broadcast(about), F.col("source").eqNullSafe(F.col("_mk"))).where(F.col("size") * LARGE > F.col("source_size"))
    first = choose_large([(r["source"], r["size"], r["_mh"]) for r in large.collect()], {k: t % s if s else 0.0 for k, _, s, t, *_ in plan})
    about = spark.createDataFrame([(*p, first.get(p[0], [])) for p in plan], "_mk string, _mn int, source_size long, target double, _mb long, _mc int, _mg array<long>")
    spread = "cast(floor(_mh / 1152921504606846976D * _mb) as long)"
    range_of = F.expr(f"if(size * {LARGE} <= source_size, {spread}, if(array_contains(_mg, _mh), -1L, _mb))")
    slim, sized = (x.join(F.broadcast(about), F.col("source").eqNullSafe(F.col("_mk"))).withColumn("_mr", range_of).drop("_mk", "_mg") for x in (slim, sized))
    ranges = slim.groupBy("_mn", "_mr").agg(F.sum("size").alias("_ms"))
    ranges = ranges.withColumn("_mo", F.expr("coalesce(sum(_ms) over (partition by _mn order by _mr rows between unbounded preceding and 1 preceding), 0)")).drop("_ms")
    # join and window share their keys (a source's number, a range): texts cross one exchange for both
    begun = sized.join(ranges, ["_mn", "_mr"])
    placed = begun.withColumn("_mi", F.expr("_mo + coalesce(sum(size) over (partition by _mn, _mr order by if(_mr = _mb, size, 0), _mh, doc_id, size rows between unbounded preceding and 1 preceding), 0)"))
    placed = placed.withColumn("_ma", F.expr(f"filter(transform(sequence(0, {int(most + 0.999)}), p -> p * source_size + _mi), c -> c + size / 2 < target)"))
    spot = "case _mc " + " ".join(f"when {i} then {position('(c / target)', demand_pieces(k))}" for i, k in enumerate(schedules)) + " end"
    return placed.withColumns({"copies": F.size("_ma").cast("long"), "positions": F.expr(f"transform(_ma, c -> {spot})")}).withColumn("taken", F.col("copies") * F.col("size")).drop(
        "_mh", "_mn", "_mb", "_mc", "_mr", "_mo", "_mi", "_ma"
    )


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: rows of docs, all columns, one for each copy taken, range-sorted by training position."""
    taken = mix(docs, **options).withColumn("_at", F.explode("positions"))
    return taken.orderBy("_at", "doc_id").select(*docs.columns)


def op4_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return mix(docs).select("doc_id", "size", "source_size", "target", "taken", "copies", F.round(F.get("positions", F.lit(0)), 6).alias("first_position"))


def _oracle(rounds: int = 12) -> str:
    """The same rows in SQL: resharing unrolled, large documents fitted by recursion."""
    weigh = " ".join(f"when {i} then {w!r}" for i, w in enumerate(WEIGHTS))
    steps = [f"r0 as (select source, size, w, null::double as target, {SHARE!r} * (select sum(size) from s) as remains from s where size > 0)"]
    for k in range(rounds):
        steps.append(f"o{k} as (select *, target is null as free, remains * w / sum(case when target is null then w end) over () as part from r{k})")
        steps.append(f"f{k} as (select *, free and part > {MOST!r} * size as over, max(free and part > {MOST!r} * size) over () as any_over from o{k})")
        steps.append(
            f"r{k + 1} as (select source, size, w, case when over then {MOST!r} * size when free and not any_over then part else target end as target, remains - coalesce(sum(case when over then {MOST!r} * size end) over (), 0) as remains from f{k})"
        )
    curve = " ".join(f"when {i} then {_position_sql(k)}" for i, k in enumerate(SCHEDULES))
    return f"""
with recursive d as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as size,
  ('0x' || substr(sha256('11:' || coalesce(doc_id::varchar, sha256(text), '')), 1, 15))::bigint as h from documents),
s as (select source, sum(size)::bigint as size, count(*) as n, case ((row_number() over (order by source nulls last)) - 1) % {len(WEIGHTS)} {weigh} end as w,
  ((row_number() over (order by source nulls last)) - 1) % {len(SCHEDULES)} as c from d group by source),
{", ".join(steps)},
plan as (select s.source, s.size as source_size, s.c, coalesce(r.target, 0)::double as target, greatest(1, (s.n + {BUCKET - 1}) // {BUCKET}) as ranges from s left join r{rounds} r on r.source is not distinct from s.source),
big as (select d.source, d.size, d.h, row_number() over (partition by d.source order by d.size desc, d.h) as i from d join plan p on p.source is not distinct from d.source where d.size * {LARGE} > p.source_size),
fit as (select source, 0::bigint as i, case when source_size > 0 then target - floor(target / source_size) * source_size else 0 end as remains, null::bigint as h, false as fits from plan
  union all select b.source, b.i, case when b.size <= f.remains then f.remains - b.size else f.remains end, b.h, b.size <= f.remains from fit f join big b on b.source is not distinct from f.source and b.i = f.i + 1),
e as (select d.*, p.*exclude(source), case when d.size * {LARGE} <= p.source_size then floor(h / 1152921504606846976.0::double * ranges)::bigint
  when exists (select 1 from fit f where f.fits and f.h = d.h and f.source is not distinct from d.source) then -1 else ranges end as r from d join plan p on p.source is not distinct from d.source),
o as (select *, coalesce(sum(size) over (partition by source order by r, case when r = ranges then size else 0 end, h, doc_id, size rows between unbounded preceding and 1 preceding), 0)::double as c0 from e),
t as (select *, (case when c0 + size / 2.0::double < target then 1 else 0 end + case when source_size + c0 + size / 2.0::double < target then 1 else 0 end)::bigint as copies from o)
select doc_id, size::bigint as size, source_size::bigint as source_size, target, copies * size::bigint as taken, copies, case when copies > 0 then round(case c {curve} end, 6) end as first_position from t
"""


def _position_sql(knots: tuple[tuple[float, float], ...]) -> str:
    """Only schedules of one piece: time t with weight * t + slope * t * t / 2 = share."""
    (_, _, weight, slope, _), *rest = demand_pieces(knots)
    assert not rest
    return f"2 * (c0 / target) / ({weight!r} + sqrt(greatest({weight!r} * {weight!r} + 2 * {slope!r} * (c0 / target), 0)) + 1e-300)"


QUERIES = {"op4_mix_sources": op4_mix_sources}
ORACLES = {"op4_mix_sources": _oracle()}
