"""SQL of the samplers: the join is made in full, numbered in the order of ranked access, and sampled with the same uniforms."""

from __future__ import annotations

from joinpoisson.functions.algebra import PRODUCT, Algebra, score_sql
from joinpoisson.functions.rng import u01_sql
from joinpoisson.operators.ranks import CHUNK_HITS
from joinpoisson.plans.jointree import Node, build_join_tree
from joinpoisson.sources.workloads import NUMBERED, WORKLOADS, Rel, Workload, join_sql, relation_sql

TURNS = 220  # gaps that a chunk of CHUNK_HITS expected hits never uses up


def tree_of(work: Workload) -> Node:
    return build_join_tree({r.name: tuple(r.attrs) for r in work.rels}, work.root)


def _sub(node: Node, algebra: Algebra, cap: int) -> str:
    return algebra.combine_sql([f"phi_{node.name}", *[_sub(c, algebra, cap) for c in node.children]], cap)


def _order(node: Node) -> list[str]:
    return [f"rid_{node.name}", *[f"sub_{c.name}" for c in node.children], *[k for c in node.children for k in _order(c)]]


def scored(work: Workload, algebra: Algebra, cap: int) -> str:
    """CTEs j, scored: all results with score (as score), sub_<relation> and weight."""
    tree = tree_of(work)
    names = [r.name for r in work.rels]
    phi = ", ".join(f"{'0' if algebra.name == 'constant' else score_sql(f'w_{n}', cap)} AS phi_{n}" for n in names)
    subs = ", ".join(f"{_sub(n, algebra, cap)} AS sub_{n.name}" for n in tree.walk())
    where = " WHERE " + " AND ".join(f"w_{n} > 0" for n in names) if algebra.drops_zero else ""
    weight = algebra.weight_sql([f"w_{n}" for n in sorted(names)])
    return f"j AS ({join_sql(work)}), phis AS (SELECT *, {phi} FROM j{where}), scored AS (SELECT *, {subs}, sub_{tree.name} AS score, {weight} AS weight FROM phis)"


def ranked(work: Workload, algebra: Algebra, cap: int) -> str:
    """CTEs up to ranked: results with rank within their score."""
    tree = tree_of(work)
    return scored(work, algebra, cap) + f", ranked AS (SELECT *, CAST(row_number() OVER (PARTITION BY score ORDER BY {', '.join(_order(tree))}) AS BIGINT) AS rank FROM scored)"


def hits(parts: str, seed: int, draw: str = "0", purpose: str = "gap") -> str:
    """CTE hits from a CTE of parts (part, n, p and, with draw = 'draw', draw): part, rank."""
    many = ", draw" if draw == "draw" else ""
    u = u01_sql(str(seed), draw, f"'{purpose}'", "part", "chunk", "turn")
    return f"""lengths AS (SELECT *, CAST(least(ceil({CHUNK_HITS}.0e0 / p), 4611686018427387904.0e0) AS BIGINT) AS length FROM {parts} WHERE n > 0 AND p > 0),
    chunks AS (SELECT *, unnest(range(0, CAST((n + length - 1) // length AS BIGINT))) AS chunk FROM lengths),
    rooms AS (SELECT *, least(length, n - chunk * length) AS room FROM chunks),
    turns AS (SELECT *, unnest(range(1, {TURNS + 1})) AS turn FROM rooms),
    gaps AS (SELECT *, CASE WHEN p >= 1 THEN 0 ELSE CAST(floor(least(CAST(room AS DOUBLE), ln({u}) / ln(1.0e0 - p))) AS BIGINT) END AS gap FROM turns),
    places AS (SELECT *, sum(gap + 1) OVER (PARTITION BY part, chunk{many} ORDER BY turn) AS place FROM gaps),
    hits AS (SELECT part{many}, p, CAST(chunk * length + place AS BIGINT) AS rank FROM places WHERE place <= room)"""


def gated_hits(parts: str, seed: int) -> str:
    """The same from parts (part, n, p) behind a gate: first whether a part has a hit, then the first, then the rest."""
    gate, first = (u01_sql(str(seed), "0", f"'{x}'", "part") for x in ("gate", "first"))
    miss = "(CASE WHEN p >= 1 THEN 0.0e0 ELSE exp(n * ln(1.0e0 - p)) END)"
    return f"""opened AS (SELECT *, CASE WHEN p >= 1 THEN 0 ELSE CAST(least(floor(ln(1.0e0 - (1.0e0 - {miss}) * {first}) / ln(1.0e0 - p)), n - 1) AS BIGINT) END + 1 AS begun FROM {parts} WHERE {gate} < 1.0e0 - {miss}),
    behind AS (SELECT part, n - begun AS n, p, begun FROM opened), {hits('behind', seed).replace('hits AS', 'later AS')},
    hits AS (SELECT part, p, begun AS rank FROM opened UNION ALL SELECT l.part, l.p, l.rank + o.begun FROM later l JOIN opened o ON l.part = o.part)"""


def power_up(x: str) -> str:
    return f"CAST(CASE WHEN {x} <= 1 THEN {x} ELSE pow(2, ceil(log2({x}))) END AS BIGINT)"


def counted(work: Workload, cap: int, rounded: bool = True, grid: bool = False, only: str = "true") -> str:
    """CTEs of an index of products made from counts, as the maintained one is: for every relation t_ (tuples with their
    score; only: a condition on relation and rid_<relation>), p_ (places with lo), m_ (counts by key and score: raw, n) and
    r_ (results of its subtree with their rank). rounded: parents see counts rounded up; grid: scores are lists, as text."""
    rels, ctes = {r.name: r for r in work.rels}, []
    for node in reversed(tree_of(work).walk()):
        name, kids = node.name, [c.name for c in node.children]
        own = f"CAST({score_sql(f'w_{name}', cap)} AS {'VARCHAR' if grid else 'INTEGER'})"
        ctes.append(f"t_{name} AS (SELECT *, {own} AS phi FROM ({relation_sql(rels[name])}) WHERE w_{name} > 0 AND ({only.format(rel=name)}))")
        parts = ["t.phi", *[f"m_{c}.score" for c in kids]]
        score = f"concat_ws('-', {', '.join(parts)})" if grid else f"CAST(least({cap}, {' + '.join(parts)}) AS INTEGER)"
        joins = " ".join(f"JOIN m_{c.name} ON {' AND '.join(f't.{k} = m_{c.name}.{k}' for k in c.key) or 'true'}" for c in node.children)
        more = "".join(f", m_{c}.score AS score_{c}, m_{c}.n AS n_{c}" for c in kids)
        group = ", ".join([*node.key, "score"])
        order = ", ".join([f"rid_{name}", *[f"score_{c}" for c in kids]])
        ctes.append(f"q_{name} AS (SELECT t.*, {score} AS score{more}, {' * '.join(f'm_{c}.n' for c in kids) or '1'} AS places_n FROM t_{name} t {joins})")
        ctes.append(f"p_{name} AS (SELECT *, coalesce(sum(places_n) OVER (PARTITION BY {group} ORDER BY {order} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS lo FROM q_{name})")
        ctes.append(f"m_{name} AS (SELECT {group}, CAST(sum(places_n) AS BIGINT) AS raw, {power_up('sum(places_n)') if rounded else 'CAST(sum(places_n) AS BIGINT)'} AS n FROM q_{name} GROUP BY {group})")
        inside = [" * ".join([f"(r_{c}.rank - 1)", *[f"p.n_{k}" for k in kids[i + 1 :]]]) for i, c in enumerate(kids)]
        below = [n for c in node.children for n in c.names]
        shown = [*[f"p.{k}" for k in node.key], "p.score", f"p.rid_{name}", f"p.w_{name}", *[f"r_{c.name}.{x}_{n}" for c in node.children for n in c.names for x in ("rid", "w")]]
        met = " ".join(f"JOIN r_{c.name} ON p.score_{c.name} = r_{c.name}.score{''.join(f' AND p.{k} = r_{c.name}.{k}' for k in c.key)}" for c in node.children)
        ctes.append(f"r_{name} AS (SELECT {', '.join(shown)}, CAST(p.lo + 1{''.join(' + ' + x for x in inside)} AS BIGINT) AS rank FROM p_{name} p {met})")
        assert len(below) == len(set(below))
    return ", ".join(ctes)


def counted_sample(work: Workload, cap: int, seed: int, rounded: bool = True, grid: bool = False) -> str:
    """rid_*, weight of a draw from that index, score as text."""
    root = tree_of(work).name
    value = "list_sum(CAST(string_split(score, '-') AS INTEGER[]))" if grid else "score"
    weight = " * ".join(f"w_{n}" for n in sorted(r.name for r in work.rels))
    return f"""WITH {counted(work, cap, rounded, grid)}, parts AS (SELECT CAST(score AS VARCHAR) AS part, CAST(sum(places_n) AS BIGINT) AS n, CAST(pow(2.0e0, -({value})) AS DOUBLE) AS p FROM p_{root} GROUP BY score), {hits('parts', seed)}
    SELECT {rids(work)}, round({weight}, 9) AS weight FROM r_{root} r JOIN hits h ON CAST(r.score AS VARCHAR) = h.part AND r.rank = h.rank WHERE {coin(work, seed)} * h.p < {weight}"""


def of_batches(work: Workload, batch_of: str, batches: int) -> list[tuple[int, int, Workload]]:
    """(batch, delta, workload over what the delta joins): the new results of each batch, relation by relation. batch_of:
    an expression of _rid_ (a tuple's rid)."""
    out = []
    for b in range(batches):
        for i, fresh in enumerate(work.rels):
            rels = []
            for j, r in enumerate(work.rels):
                source = f"(SELECT *, row_number() OVER (ORDER BY {', '.join(NUMBERED[r.table])}) AS _rid FROM {r.table})" if r.table in NUMBERED else r.table
                sign = "=" if j == i else "<=" if j < i else "<"
                rels.append(Rel(r.name, f"(SELECT * FROM {source} WHERE {batch_of.replace('_rid_', f'({r.rid})')} {sign} {b})", r.attrs, r.weight, r.rid))
            if b or i == len(work.rels) - 1:  # before the first batch there are no tuples behind the fresh one
                out.append((b, i if b else 0, Workload(work.name, tuple(rels), fresh.name)))
    return out


def maintained(work: Workload, cap: int, seed: int, batch_of: str, batches: int) -> str:
    """The maintained sample: each delta join sampled through an index of its own, rooted at the new tuples."""
    from joinpoisson.operators.dynamic import delta_seed

    parts = []
    for b, i, delta in of_batches(work, batch_of, batches):
        parts.append(f"SELECT {rids(work)} FROM ({index_sample(delta, PRODUCT, cap, delta_seed(seed, b, i))})")
    return " UNION ALL ".join(parts)


def coin(work: Workload, seed: int, draw: str = "0", purpose: str = "keep") -> str:
    return u01_sql(str(seed), draw, f"'{purpose}'", *[f"rid_{n}" for n in sorted(r.name for r in work.rels)])


def rids(work: Workload) -> str:
    return ", ".join(f"rid_{r.name}" for r in work.rels)


def index_sample(name: str | Workload, algebra: Algebra, cap: int, seed: int, draws: int = 1, gate: bool = False, last: str = "") -> str:
    """last: the number of ranks that the cap's bucket is taken to have, where it isn't counted."""
    work = WORKLOADS[name] if isinstance(name, str) else name
    draw = "draw" if draws > 1 else "0"
    k = len(work.rels)
    many = f", unnest(range(0, {draws})) AS draw" if draws > 1 else ""
    size = f"CASE WHEN score = {cap} THEN {last} ELSE count(*) END" if last else "count(*)"
    parts = f"sizes AS (SELECT score, {size} AS n, CAST(score AS VARCHAR) AS part FROM scored GROUP BY score), parts AS (SELECT *, CAST({algebra.ceiling_sql('score', k)} AS DOUBLE) AS p{many} FROM sizes)"
    shown = "h.draw, " if draws > 1 else ""
    return f"""WITH {ranked(work, algebra, cap)}, {parts}, {gated_hits('parts', seed) if gate else hits('parts', seed, draw)}
    SELECT {shown}{rids(work)}, r.score, r.rank, round(weight, 9) AS weight FROM ranked r JOIN hits h ON CAST(r.score AS VARCHAR) = h.part AND r.rank = h.rank
    WHERE {coin(work, seed, 'h.draw' if draws > 1 else '0')} * h.p < weight"""


def root_local(name: str, algebra: Algebra, cap: int, seed: int) -> str:
    work = WORKLOADS[name]
    tree = tree_of(work)
    group = [f"rid_{tree.name}", *[f"sub_{c.name}" for c in tree.children]]
    label = "concat_ws('-', " + ", ".join(f"CAST({g} AS VARCHAR)" for g in group) + ")"
    inner = [k for c in tree.children for k in _order(c)]
    return f"""WITH {scored(work, algebra, cap)},
    ranked AS (SELECT *, {label} AS part, CAST(row_number() OVER (PARTITION BY {', '.join(group)} ORDER BY {', '.join(inner) or '1'}) AS BIGINT) AS rank FROM scored),
    parts AS (SELECT part, count(*) AS n, CAST(any_value({algebra.ceiling_sql('score', len(work.rels))}) AS DOUBLE) AS p FROM ranked GROUP BY part),
    {hits('parts', seed, '0', 'local')}
    SELECT {rids(work)}, r.score, round(weight, 9) AS weight FROM ranked r JOIN hits h ON r.part = h.part AND r.rank = h.rank WHERE {coin(work, seed)} * h.p < weight"""


def naive(name: str | Workload, algebra: Algebra, seed: int, draws: int = 1) -> str:
    """CTEs j, naive: the join-first sample of each draw."""
    work = WORKLOADS[name] if isinstance(name, str) else name
    weight = algebra.weight_sql([f"w_{n}" for n in sorted(r.name for r in work.rels)])
    return f"""j AS ({join_sql(work)}), weighed AS (SELECT *, {weight} AS weight, unnest(range(0, {draws})) AS draw FROM j),
    naive AS (SELECT * FROM weighed WHERE {coin(work, seed, 'draw', 'naive')} < weight)"""
