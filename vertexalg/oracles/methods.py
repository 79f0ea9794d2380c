"""SQL forms of the methods over any edge SQL (src, dst, value)."""

from __future__ import annotations


def _edges(sql: str, name: str = "e") -> str:
    return f"{name} as materialized ({sql})"


def symmetric(sql: str) -> str:
    return f"select src, dst, min(value) as value from (select src, dst, value from ({sql}) union all select dst, src, value from ({sql})) where src <> dst group by all"


def upper(sql: str) -> str:
    return f"select distinct least(src, dst) as src, greatest(src, dst) as dst from ({sql}) where src <> dst"


def degree(sql: str, vertices: str, end: str) -> str:
    return f"with {_edges(sql)}, v as ({vertices}) select vid, count({end}) as degree from v left join e on e.{end} = v.vid group by vid"


def _rank_steps(sql: str, vertices: str, rounds: int, r: float) -> str:
    """CTEs r0 .. r{rounds} (vid, rank, d): every vertex sends and is updated in each round."""
    steps = [f"r0 as materialized (select vid, 1.0::double as rank, coalesce(n, 0) as d from v left join (select src, count(*) as n from e group by src) o on o.src = v.vid)"]
    for i in range(rounds):
        steps.append(f"r{i + 1} as materialized (select p.vid, {r}::double + {1 - r}::double * coalesce(s, 0) as rank, p.d from r{i} p left join (select e.dst, sum(q.rank / q.d) as s from e join r{i} q on q.vid = e.src group by e.dst) y on y.dst = p.vid)")
    return f"with {_edges(sql)}, v as ({vertices}), {', '.join(steps)}"


def rank(sql: str, vertices: str, rounds: int = 10, r: float = 0.15, digits: int = 6) -> str:
    return f"{_rank_steps(sql, vertices, rounds, r)} select vid, round(rank, {digits}) as rank from r{rounds}"


def rank_until(sql: str, vertices: str, tol: float, most: int = 30, r: float = 0.15) -> str:
    """Ranks after the first round in which none moves by more than tol (no row if that takes more than most rounds)."""
    moves = " union all ".join(f"select {i} as k, max(abs(a.rank - b.rank)) as m from r{i} a join r{i - 1} b using (vid)" for i in range(1, most + 1))
    every = " union all ".join(f"select {i} as k, vid, rank from r{i}" for i in range(1, most + 1))
    return f"{_rank_steps(sql, vertices, most, r)}, m as materialized ({moves}) select vid, round(rank, 6) as rank from ({every}) where k = (select min(k) from m where m <= {tol})"


def rank_recipients(sql: str, vertices: str, rounds: int = 10, r: float = 0.15) -> str:
    """The plain rule of a superstep: who changed in the last round sends, and who gets something is updated."""
    steps = [f"r0 as materialized (select vid, 1.0::double as rank, coalesce(n, 0) as d, true as go from v left join (select src, count(*) as n from e group by src) o on o.src = v.vid)"]
    for i in range(rounds):
        got = f"select e.dst, {r}::double + {1 - r}::double * sum(q.rank / q.d) as new from e join r{i} q on q.vid = e.src where q.go group by e.dst"
        steps.append(f"r{i + 1} as materialized (select p.vid, coalesce(new, p.rank) as rank, p.d, new is not null and new <> p.rank as go from r{i} p left join ({got}) y on y.dst = p.vid)")
    return f"with {_edges(sql)}, v as ({vertices}), {', '.join(steps)} select vid, round(rank, 6) as rank from r{rounds}"


def paths(sql: str, vertices: str, root: str, weight: str = "value", name: str = "dist") -> str:
    """Distances of all vertices from root (a scalar SQL), null where unreached."""
    return (
        f"with recursive {_edges(sql)}, v as ({vertices}), k(vid, d) using key (vid) as (select ({root})::bigint, 0::bigint union "
        f"select e.dst, min(k.d + {weight}) from k join e on e.src = k.vid left join recurring.k o on o.vid = e.dst group by e.dst, o.d having o.d is null or min(k.d + {weight}) < o.d) "
        f"select v.vid, k.d as {name} from v left join k on k.vid = v.vid"
    )


def triangles(sql: str) -> str:
    return f"with {_edges(upper(sql))} select count(*) as triangles from e a join e b on a.dst = b.src join e c on c.src = a.src and c.dst = b.dst"


def triangle_rows(sql: str) -> str:
    return f"with {_edges(upper(sql))} select a.src as u, a.dst as v, b.dst as w from e a join e b on a.dst = b.src join e c on c.src = a.src and c.dst = b.dst"


def triangles_per_vertex(sql: str, vertices: str) -> str:
    return f"with t as materialized ({triangle_rows(sql)}), p as (select u as vid from t union all select v from t union all select w from t), v as ({vertices}) select v.vid, count(p.vid) as triangles from v left join p on p.vid = v.vid group by v.vid"


def components(sql: str, vertices: str) -> str:
    return (
        f"with recursive {_edges(symmetric(sql))}, v as ({vertices}), k(vid, c) using key (vid) as (select vid, vid from v union "
        f"select e.dst, min(k.c) from k join e on e.src = k.vid join recurring.k o on o.vid = e.dst group by e.dst, o.c having min(k.c) < o.c) select vid, c as component from k"
    )


def factors(ratings: str, k: int, rounds: int, gamma: float = 0.002, lam: float = 0.05, fresh: bool = False) -> str:
    """CTEs r (user, item, rating) and f (side, id, l list) after the rounds. fresh: items move after users, from where they have come to."""
    first = ", ".join(f"(1 + (id * 7 + {i * 13} + side * 5) % 10) / 10.0" for i in range(k))
    parts = [f"r as materialized ({ratings})", f"f0 as materialized (select side, id, [{first}]::double[] as l from (select distinct 0 as side, \"user\" as id from r union all select distinct 1, item from r))"]
    sums = ", ".join(f"sum(e * o[{j + 1}])" for j in range(k))
    moved = ", ".join(f"l[{j + 1}] + {gamma} * (g[{j + 1}] - {lam} * l[{j + 1}])" for j in range(k))
    sides = {0: f"select 0 as side, \"user\" as id, [{sums}] as g from (select *, q as o from {{b}}) group by \"user\"", 1: f"select 1 as side, item as id, [{sums}] as g from (select *, p as o from {{b}}) group by item"}
    step = 0
    for _ in range(rounds):
        for part in ((0,), (1,)) if fresh else ((0, 1),):
            i, step = step, step + 1
            both = f"select r.\"user\", r.item, p.l as p, q.l as q, r.rating - list_dot_product(p.l, q.l) as e from r join f{i} p on p.side = 0 and p.id = r.\"user\" join f{i} q on q.side = 1 and q.id = r.item"
            parts.append(f"b{i} as materialized ({both}), g{i} as ({' union all '.join(sides[n].format(b=f'b{i}') for n in part)})")
            parts.append(f"f{step} as materialized (select side, id, case when g is null then l else [{moved}]::double[] end as l from f{i} left join g{i} using (side, id))")
    parts.append(f"f as (select * from f{step})")
    return ", ".join(parts)


PREDICTED = "select r.*, list_dot_product(p.l, q.l) as prediction, p.l as p, q.l as q from r join f p on p.side = 0 and p.id = r.\"user\" join f q on q.side = 1 and q.id = r.item"
