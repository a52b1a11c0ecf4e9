"""SQL of the method queries' oracles, for DuckDB: fixtures and unrolled iterations."""

from __future__ import annotations

import numpy as np

from meshprofile.functions.hashing import lane_duck, uniform_duck
from meshprofile.sources.tables import CENTRES, WIDTHS


def raw_slots(slots: int) -> str:
    """grid(id, slot, v): summed readings, zero where there are none."""
    return f"""raw as (select user_id as id, (hour(ts) * 60 + minute(ts)) // {1440 // slots} as slot, sum(value) as v from events group by all),
grid as (select u.id, r.s as slot, coalesce(raw.v, 0) as v from (select distinct user_id as id from events) u cross join range({slots}) r(s) left join raw on raw.id = u.id and raw.slot = r.s)"""


def peak_profiles(slots: int) -> str:
    """p(party, id, slot, y): peak-scaled, over ten parties."""
    return raw_slots(slots) + ",\np as (select (id % 10)::int as party, id, slot, coalesce(v / nullif(max(v) over (partition by id), 0), 0) as y from grid)"


def planted(slots: int) -> str:
    at, width = ("[" + ", ".join(map(str, v)) + "]" for v in (CENTRES, WIDTHS))
    noise = uniform_duck(f"'11:' || id || ':' || (s * {48 // slots})")
    return f"""c as (select c_custkey::bigint as id, (c_custkey % 6)::int as archetype, ((c_custkey // 6) % 10)::int as home from customer),
h as (select id, archetype, (case when home = 0 and archetype not in (1, 2) then 1 + (id // 60) % 9 else home end)::int as party, {at}[archetype + 1] as centre, {width}[archetype + 1] as width from c),
p as (select party, id, archetype, s as slot, 0.1 + exp(-((s * {48 // slots} - centre) ^ 2) / (2.0 * width * width)) + 0.5 * ({noise} - 0.5) as y from h, range({slots}) r(s))"""


def values(rows, names: str) -> str:
    return f"(values {', '.join('(' + ', '.join(repr(v) for v in r) + ')' for r in rows)}) as v({names})"


def weights(w: np.ndarray) -> str:
    return "w as (select * from " + values([(i, j, float(w[i, j])) for i in range(len(w)) for j in range(len(w)) if w[i, j]], "dst, src, w") + ")"


def draw(nonce: str, sigma: float, beta: float, t: int) -> str:
    """A party's draw of round t under the fixed secrets s0, s1, ..."""
    key = f"'s' || party || ':{nonce}:' || party || ':' || (comp // 8) || ':{t}'"
    return f"({lane_duck(key, 'comp % 8')} - 0.5) * {sigma!r} * {beta ** (t + 1)!r}"


def theta(nonce: str, sigma: float, beta: float, t: int) -> str:
    return draw(nonce, sigma, beta, t) + (f" - {draw(nonce, sigma, beta, t - 1)}" if t else "")


def trace(state: str, w: np.ndarray, rounds: int, sigma: float, beta: float, nonce: str = "0") -> str:
    """CTEs x0..xR and m0..m(R-1) from `state(party, comp, x)`: unrolled rounds."""
    out = [weights(w), f"x0 as materialized (select party, comp, x from {state})"]
    for t in range(rounds):
        mask = theta(nonce, sigma, beta, t) if sigma else "0"
        out.append(f"m{t} as materialized (select {t} as t, party, comp, x + {mask} as shared, x as state from x{t})")
        out.append(f"x{t + 1} as materialized (select w.dst as party, comp, sum(w.w * shared) as x from m{t} join w on w.src = m{t}.party group by all)")
    return ",\n".join(out)


def traces(state: str, kinds: dict[str, tuple[np.ndarray, float]], rounds: int, beta: float) -> str:
    """The same for several kinds (name -> weights, sigma) side by side: `all_m(kind, t, party, comp, shared, state)`."""
    rows = [(kind, i, j, float(w[i, j])) for kind, (w, _) in kinds.items() for i in range(len(w)) for j in range(len(w)) if w[i, j]]
    masked = ", ".join(f"'{k}'" for k, (_, s) in kinds.items() if s)
    sigma = max(s for _, s in kinds.values())
    out = ["w as (select * from " + values(rows, "kind, dst, src, w") + ")", f"x0 as materialized (select kind, party, comp, x from {state}, (select distinct kind from w))"]
    for t in range(rounds):
        out.append(f"m{t} as materialized (select {t} as t, kind, party, comp, x + case when kind in ({masked}) then {theta('0', sigma, beta, t)} else 0 end as shared, x as state from x{t})")
        out.append(f"x{t + 1} as materialized (select w.kind, w.dst as party, comp, sum(w.w * shared) as x from m{t} join w on w.src = m{t}.party and w.kind = m{t}.kind group by all)")
    return ",\n".join([*out, "all_m as (" + " union all ".join(f"select * from m{t}" for t in range(rounds)) + ")"])


def start_model(mu: np.ndarray) -> str:
    return "m0 as materialized (select * from " + values([(k, s, float(mu[k, s])) for k in range(len(mu)) for s in range(mu.shape[1])], "k, slot, mu") + ")"


def _distances(t: int) -> str:
    return f"d{t} as materialized (select p.party, p.id, m.k, sum((p.y - m.mu) ^ 2) as d2 from p join m{t} m on m.slot = p.slot group by all)"


def _nearest(t: int) -> str:
    return f"a{t} as materialized (select party, id, k, d2 from (select *, row_number() over (partition by id order by d2, k) as rn from d{t}) where rn = 1)"


def kmeans(mu: np.ndarray, rounds: int) -> str:
    """CTEs m0..mT (k, slot, mu) and a0..aT over p."""
    out = [start_model(mu)]
    for t in range(rounds):
        out += [_distances(t), _nearest(t)]
        out.append(f"m{t + 1} as materialized (select m.k, m.slot, coalesce(avg(p.y), m.mu) as mu from m{t} m left join a{t} a on a.k = m.k left join p on p.id = a.id and p.slot = m.slot group by m.k, m.slot, m.mu)")
    return ",\n".join([*out, _distances(rounds), _nearest(rounds)])


def fuzzy(mu: np.ndarray, rounds: int, power: int, m: float = 2.0) -> str:
    out = [start_model(mu)]
    for t in range(rounds):
        out.append(_distances(t))
        out.append(f"u{t} as materialized (select id, k, (v / sum(v) over (partition by id)) ^ {power} as g from (select id, k, d2 ^ {-1 / (m - 1)!r} as v from d{t}))")
        out.append(f"m{t + 1} as materialized (select u.k, p.slot, sum(u.g * p.y) / sum(u.g) as mu from u{t} u join p on p.id = u.id group by all)")
    return ",\n".join(out)


def gmm_diag(mu: np.ndarray, rounds: int, variance: float, reg: float) -> str:
    """CTEs m0..mT (k, slot, mu, var) and w0..wT (k, weight)."""
    k = len(mu)
    rows = values([(i, s, float(mu[i, s]), variance) for i in range(k) for s in range(mu.shape[1])], "k, slot, mu, var")
    out = [f"m0 as materialized (select * from {rows})", f"w0 as materialized (select range as k, {1 / k!r} as weight from range({k}))"]
    for t in range(rounds):
        out.append(f"l{t} as materialized (select p.id, m.k, ln(any_value(w.weight)) - 0.5 * sum(ln(2 * pi()) + ln(m.var) + (p.y - m.mu) ^ 2 / m.var) as l from p join m{t} m on m.slot = p.slot join w{t} w on w.k = m.k group by p.id, m.k)")
        out.append(f"q{t} as materialized (select id, k, e / sum(e) over (partition by id) as q from (select id, k, exp(l - max(l) over (partition by id)) as e from l{t}))")
        out.append(f"s{t} as materialized (select q.k, p.slot, sum(q) as z, sum(q * p.y) / sum(q) as mu, sum(q * (p.y - m.mu) ^ 2) / sum(q) as h, any_value(m.mu) as old from q{t} q join p on p.id = q.id join m{t} m on m.k = q.k and m.slot = p.slot group by all)")
        out.append(f"m{t + 1} as materialized (select k, slot, mu, greatest(h - (mu - old) ^ 2, 0) + {reg!r} as var from s{t})")
        out.append(f"w{t + 1} as materialized (select k, any_value(z) / (select sum(z) from s{t} where slot = 0) as weight from s{t} where slot = 0 group by k)")
    return ",\n".join(out)


# several fits side by side: `fits(g, src)` names them and the rows of `p(src, id, slot, y)` they take -------------


def fits(named: dict[int, str]) -> str:
    return "fits as (select * from " + values(list(named.items()), "g, src") + ")"


def _starts(name: str, starts: dict[int, np.ndarray]) -> str:
    rows = [(g, k, s, float(mu[k, s])) for g, mu in starts.items() for k in range(len(mu)) for s in range(mu.shape[1])]
    return f"{name} as materialized (select * from " + values(rows, "g, k, slot, mu") + ")"


def many_kmeans(pre: str, starts: dict[int, np.ndarray], rounds: int) -> str:
    """CTEs {pre}m0..{pre}mT (g, k, slot, mu) and {pre}a(g, id, k)."""
    out = [_starts(f"{pre}m0", starts)]
    for t in range(rounds + 1):
        out.append(f"{pre}d{t} as materialized (select f.g, p.id, m.k, sum((p.y - m.mu) ^ 2) as d2 from fits f join p on p.src = f.src join {pre}m{t} m on m.g = f.g and m.slot = p.slot group by all)")
        out.append(f"{pre}{f'a{t}' if t < rounds else 'a'} as materialized (select g, id, k, d2 from (select *, row_number() over (partition by g, id order by d2, k) as rn from {pre}d{t}) where rn = 1)")
        if t < rounds:
            out.append(
                f"{pre}m{t + 1} as materialized (select m.g, m.k, m.slot, coalesce(x.mu, m.mu) as mu from {pre}m{t} m left join (select a.g, a.k, p.slot, avg(p.y) as mu from {pre}a{t} a join fits f on f.g = a.g join p on p.src = f.src and p.id = a.id group by all) x on x.g = m.g and x.k = m.k and x.slot = m.slot)"
            )
    return ",\n".join(out)


def many_fuzzy(pre: str, starts: dict[int, np.ndarray], rounds: int) -> str:
    """The same for fuzzy c-means with exponent 2."""
    out = [_starts(f"{pre}m0", starts)]
    for t in range(rounds + 1):
        out.append(f"{pre}d{t} as materialized (select f.g, p.id, m.k, sum((p.y - m.mu) ^ 2) as d2 from fits f join p on p.src = f.src join {pre}m{t} m on m.g = f.g and m.slot = p.slot group by all)")
        if t < rounds:
            out.append(f"{pre}u{t} as materialized (select g, id, k, (v / sum(v) over (partition by g, id)) ^ 2 as w from (select g, id, k, 1 / d2 as v from {pre}d{t}))")
            out.append(f"{pre}m{t + 1} as materialized (select u.g, u.k, p.slot, sum(u.w * p.y) / sum(u.w) as mu from {pre}u{t} u join fits f on f.g = u.g join p on p.src = f.src and p.id = u.id group by all)")
    out.append(f"{pre}a as materialized (select g, id, k from (select *, row_number() over (partition by g, id order by d2, k) as rn from {pre}d{rounds}) where rn = 1)")
    return ",\n".join(out)


def many_gmm(pre: str, starts: dict[int, np.ndarray], rounds: int, variance: float, reg: float) -> str:
    """The same for mixtures with diagonal covariances."""
    out = [_starts(f"{pre}m0", starts).replace("(select * from", f"(select *, {variance!r}::double as var from", 1), f"{pre}w0 as materialized (select g, k, 1.0::double / count(*) over (partition by g) as weight from (select distinct g, k from {pre}m0))"]
    for t in range(rounds + 1):
        out.append(
            f"{pre}l{t} as materialized (select f.g, p.id, m.k, ln(any_value(w.weight)) - 0.5 * sum(ln(2 * pi()) + ln(m.var) + (p.y - m.mu) ^ 2 / m.var) as l from fits f join p on p.src = f.src join {pre}m{t} m on m.g = f.g and m.slot = p.slot join {pre}w{t} w on w.g = f.g and w.k = m.k group by f.g, p.id, m.k)"
        )
        if t < rounds:
            out.append(f"{pre}q{t} as materialized (select g, id, k, e / sum(e) over (partition by g, id) as q from (select g, id, k, exp(l - max(l) over (partition by g, id)) as e from {pre}l{t}))")
            out.append(
                f"{pre}s{t} as materialized (select q.g, q.k, p.slot, sum(q) as z, sum(q * p.y) / sum(q) as mu, sum(q * (p.y - m.mu) ^ 2) / sum(q) as h, any_value(m.mu) as old from {pre}q{t} q join fits f on f.g = q.g join p on p.src = f.src and p.id = q.id join {pre}m{t} m on m.g = q.g and m.k = q.k and m.slot = p.slot group by all)"
            )
            out.append(f"{pre}m{t + 1} as materialized (select g, k, slot, mu, greatest(h - (mu - old) ^ 2, 0) + {reg!r} as var from {pre}s{t})")
            out.append(f"{pre}w{t + 1} as materialized (select g, k, z / sum(z) over (partition by g) as weight from {pre}s{t} where slot = 0)")
    out.append(f"{pre}a as materialized (select g, id, k from (select *, row_number() over (partition by g, id order by l desc, k) as rn from {pre}l{rounds}) where rn = 1)")
    return ",\n".join(out)


def silhouettes(pre: str) -> str:
    """CTE {pre}sil(g, silhouette): mean squared-distance silhouette of {pre}a, from each cluster's sums."""
    return f"""{pre}c as materialized (select a.g, a.k, p.slot, count(*) as n, sum(p.y) as s from {pre}a a join fits f on f.g = a.g join p on p.src = f.src and p.id = a.id group by all),
{pre}r as materialized (select src, id, sum(y * y) as r from p group by all),
{pre}q as materialized (select a.g, a.k, sum(r.r) as q from {pre}a a join fits f on f.g = a.g join {pre}r r on r.src = f.src and r.id = a.id group by all),
{pre}x as materialized (select f.g, p.id, c.k, any_value(c.n) as n, sum(p.y * c.s) as xs from fits f join p on p.src = f.src join {pre}c c on c.g = f.g and c.slot = p.slot group by f.g, p.id, c.k),
{pre}t as materialized (select x.g, x.id, x.k, x.n, x.n * r.r - 2 * x.xs + q.q as total, a.k = x.k as own from {pre}x x join fits f on f.g = x.g join {pre}r r on r.src = f.src and r.id = x.id join {pre}q q on q.g = x.g and q.k = x.k join {pre}a a on a.g = x.g and a.id = x.id),
{pre}ab as materialized (select g, id, max(n) filter (own) as n, max(total / greatest(n - 1, 1)) filter (own) as a, min(total / n) filter (not own) as b from {pre}t group by all),
{pre}sil as (select g, avg(case when b is null or n < 2 then 0 else (b - a) / greatest(a, b, 1e-300) end) as silhouette from {pre}ab group by g)"""
