"""DuckDB SQL for the workloads: self-joins over the derived edges, never the decomposition."""

from __future__ import annotations

from cutloom.operators.constraints import demo
from cutloom.patterns import Pattern, automorphisms, connected_patterns, cycle, diamond, house
from cutloom.patterns import chain as chain_of
from cutloom.plans.cuts import parts
from cutloom.queries import BASELINES, COUNTS, FRAGMENTS, SWEEP
from cutloom.sources.derive import PART_GRAPHS, SUPPLIER_OFFSET


def edges_sql(kind: str) -> str:
    """A WITH list that ends in e(src, dst) and a(u, v)."""
    if kind in PART_GRAPHS:
        e = f"l AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS k FROM lineitem WHERE {PART_GRAPHS[kind]}), e AS MATERIALIZED (SELECT DISTINCT x.k AS src, y.k AS dst FROM l x JOIN l y ON x.o = y.o AND x.k < y.k)"
    elif kind == "bip":
        e = f"e AS MATERIALIZED (SELECT DISTINCT l_partkey AS src, l_suppkey + {SUPPLIER_OFFSET} AS dst FROM lineitem WHERE l_returnflag = 'R')"
    elif kind == "act":
        e = "e AS MATERIALIZED (SELECT DISTINCT least(x.user_id, y.user_id) AS src, greatest(x.user_id, y.user_id) AS dst FROM events x JOIN events y ON x.event_type = y.event_type AND x.user_id <> y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 60 SECOND)"
    else:
        dot = "list_sum(list_transform(list_zip(x.e, y.e), lambda p: p[1] * p[2]))"
        e = f"s AS (SELECT vec_id AS k, list_transform(embedding, lambda v: v::DOUBLE) AS e FROM embeddings), e AS MATERIALIZED (SELECT x.k AS src, y.k AS dst FROM s x JOIN s y ON x.k < y.k WHERE {dot} / sqrt(list_sum(list_transform(x.e, lambda v: v * v)) * list_sum(list_transform(y.e, lambda v: v * v))) >= 0.3)"
    return f"{e}, a AS MATERIALIZED (SELECT src AS u, dst AS v FROM e UNION ALL SELECT dst, src FROM e)"


def matchings_from(p: Pattern, induced: str = "edge") -> tuple[str, str]:
    """FROM and WHERE of all matchings; vertex k is the column named by column_of()."""
    rows = sorted(p.edges)
    where = []
    for i, (x, y) in enumerate(rows):
        for v, c in ((x, f"e{i}.u"), (y, f"e{i}.v")):
            if column_of(p, v) != c:
                where.append(f"{column_of(p, v)} = {c}")
    for x in range(p.n):
        for y in range(x):
            if not p.adjacent(x, y):
                where.append(f"{column_of(p, x)} <> {column_of(p, y)}")
                if induced == "vertex":
                    where.append(f"NOT EXISTS (SELECT 1 FROM a z WHERE z.u = {column_of(p, x)} AND z.v = {column_of(p, y)})")
    return ", ".join(f"a e{i}" for i in range(len(rows))), " AND ".join(where) or "true"


def column_of(p: Pattern, v: int) -> str:
    for i, (x, y) in enumerate(sorted(p.edges)):
        if x == v:
            return f"e{i}.u"
        if y == v:
            return f"e{i}.v"
    raise ValueError(v)


def count_sql(patterns, kind: str, induced: str) -> str:
    out = []
    for p in patterns:
        tables, where = matchings_from(p, induced)
        out.append(f"SELECT '{p.name}' AS pattern, {p.n} AS n, {p.m} AS m, (count(*) // {len(automorphisms(p))})::BIGINT AS cnt FROM {tables} WHERE {where}")
    return f"WITH {edges_sql(kind)} " + " UNION ALL ".join(out)


def fragments_sql(p: Pattern, cut: tuple[int, ...]) -> str:
    """Weights as how often each projection of a whole matching occurs."""
    tables, where = matchings_from(p)
    whole = f"w AS MATERIALIZED (SELECT {', '.join(f'{column_of(p, v)} AS m{v}' for v in range(p.n))} FROM {tables} WHERE {where})"
    out = []
    for i, part in enumerate(parts(p, cut)):
        own = [f"m{v}" for v in sorted(part.vertices)]
        columns = ", ".join(f"m{v}" if v in part.vertices else f"NULL::BIGINT AS m{v}" for v in range(p.n))
        out.append(f"SELECT {i} AS part, {columns}, count(*)::BIGINT AS weight FROM w GROUP BY {', '.join(own)}")
    return f"WITH {edges_sql('bulk')}, {whole} " + " UNION ALL ".join(out)


SHAPES = [("edge", Pattern.parse("01")), ("chain3", Pattern.parse("01 02")), ("triangle", Pattern.parse("01 02 12")), ("star3", Pattern.parse("01 02 03")), ("chain4", Pattern.parse("01 02 13"))]


def supports_sql(kind: str, labels: str) -> str:
    """WITH list ending in sup(shape, n_edges, l0..l3, support)."""
    out = []
    for name, p in SHAPES:
        tables, where = matchings_from(p)
        cols = ", ".join(f"{column_of(p, v)} AS m{v}, k{v}.label AS l{v}" for v in range(p.n))
        join = " ".join(f"JOIN lab k{v} ON k{v}.v = {column_of(p, v)}" for v in range(p.n))
        tables = tables.replace(", ", " CROSS JOIN ")
        sub = f"(SELECT {cols} FROM {tables} {join} WHERE {where})"
        names = [f"l{v}" for v in range(p.n)]
        smaller = " AND ".join("(" + ", ".join(names) + ") <= (" + ", ".join(f"l{x[v]}" for v in range(p.n)) + ")" for x in automorphisms(p))
        out.append(f"SELECT '{name}' AS shape, {p.m} AS n_edges, {', '.join(f'l{v}' if v < p.n else f'NULL::VARCHAR AS l{v}' for v in range(4))}, least({', '.join(f'count(DISTINCT m{v})' for v in range(p.n))})::BIGINT AS support FROM {sub} WHERE {smaller} GROUP BY {', '.join(names)}")
    return f"{edges_sql(kind)}, lab AS ({labels}), sup AS (" + " UNION ALL ".join(out) + ")"


def constraint_sql(whole: bool) -> str:
    """By labels first: triangles (1, 3, 4) of one label where they must agree, else triangles (0, 1, 3), are few; the rest is joined to them."""
    p, c, _ = demo()
    labelled = f"{edges_sql('bulk')}, t AS MATERIALIZED (SELECT u, v, x.p_type AS lu, y.p_type AS lv FROM a JOIN part x ON x.p_partkey = u JOIN part y ON y.p_partkey = v)"
    if whole:
        return f"""WITH {labelled}, s AS MATERIALIZED (SELECT * FROM t WHERE lu = lv),
low AS MATERIALIZED (SELECT x.u AS m1, x.v AS m3, y.v AS m4, x.lu AS l1 FROM s x JOIN s y ON y.u = x.v JOIN s z ON z.u = x.u AND z.v = y.v),
roof AS MATERIALIZED (SELECT low.*, x.v AS m0, x.lv AS l0 FROM low JOIN t x ON x.u = m1 AND x.lv <> l1 JOIN a y ON y.u = x.v AND y.v = m3)
SELECT count(*)::BIGINT AS matchings, count(*)::BIGINT AS subgraphs FROM roof JOIN t x ON x.u = m1 AND x.lv <> l1 AND x.lv <> l0 JOIN a y ON y.u = m0 AND y.v = x.v WHERE x.v <> m3 AND x.v <> m4 AND m0 <> m4"""
    from cutloom.operators.constraints import Constraint, preserving

    tables, where = matchings_from(p)
    tables = tables.replace(", ", " CROSS JOIN ")
    join = " ".join(f"JOIN part k{v} ON k{v}.p_partkey = {column_of(p, v)}" for v in range(p.n))
    test = "k0.p_type <> k1.p_type AND k0.p_type <> k2.p_type AND k1.p_type <> k2.p_type"
    group = len(preserving(p, Constraint(c.subs[:1])))
    return f"WITH {edges_sql('bulk')} SELECT count(*)::BIGINT AS matchings, (count(*) // {group})::BIGINT AS subgraphs FROM {tables} {join} WHERE {where} AND {test}"


def all_oracles() -> dict[str, str]:
    out = {k: count_sql(*v) for k, v in {**COUNTS, **BASELINES}.items()}
    out |= {k: fragments_sql(*v) for k, v in FRAGMENTS.items()}
    out["profiled_counts"] = count_sql((house(), cycle(5), chain_of(5), diamond()), "bulk", "edge")
    types = "SELECT p_partkey AS v, p_type AS label FROM part"
    columns = "shape, n_edges, l0, l1, l2, l3, support"
    for t in (50, 100, 150):
        out[f"fsm_t{t}"] = f"WITH {supports_sql('bulk', types)} SELECT {columns} FROM sup WHERE support >= {t}"
    out["fsm_t100_embeddings"] = out["fsm_t100_fragments"] = out["fsm_t100"]
    out["fsm_sim_t10"] = f"WITH {supports_sql('sim', 'SELECT vec_id AS v, label::VARCHAR AS label FROM embeddings')} SELECT {columns} FROM sup WHERE support >= 10"
    marks = ", ".join(f"({t})" for t in SWEEP)
    out["fsm_sweep"] = f"WITH {supports_sql('bulk', types)} SELECT t.threshold::BIGINT AS threshold, s.shape, count(sup.support)::BIGINT AS n FROM (VALUES {marks}) t(threshold) CROSS JOIN (VALUES {', '.join(f'({chr(39)}{s}{chr(39)})' for s, _ in SHAPES)}) s(shape) LEFT JOIN sup ON sup.shape = s.shape AND sup.support >= t.threshold GROUP BY ALL"
    out["star10_labels"] = f"WITH {edges_sql('bulk')} SELECT p_type AS label, count(*)::BIGINT AS n FROM (SELECT u FROM a GROUP BY u HAVING count(*) >= 10) d JOIN part ON p_partkey = u GROUP BY p_type"
    out["constraint_demo"], out["constraint_differ"] = constraint_sql(True), constraint_sql(False)
    chain, triangle = Pattern.parse("01 02"), Pattern.parse("01 02 12")
    t3, w3 = matchings_from(chain)
    tv, wv = matchings_from(chain, "vertex")
    tt, wt = matchings_from(triangle)
    out["edge_to_vertex_identity"] = f"WITH {edges_sql('bulk')} SELECT ((SELECT count(*) FROM {tv} WHERE {wv}) // 2)::BIGINT AS direct, ((SELECT count(*) FROM {t3} WHERE {w3}) // 2 - 3 * ((SELECT count(*) FROM {tt} WHERE {wt}) // 6))::BIGINT AS indirect"
    replay = [p for p in connected_patterns(5) if not p.is_clique()]
    rows = []
    for p in replay:
        tables, where = matchings_from(p)
        rows.append(f"SELECT '{p.name}' AS pattern, (count(*) // {len(automorphisms(p))})::BIGINT AS plain, (count(*) // {len(automorphisms(p))})::BIGINT AS replayed FROM {tables} WHERE {where}")
    out["replay_on_off"] = f"WITH {edges_sql('bulk')} " + " UNION ALL ".join(rows)
    square = Pattern.parse("01 12 23 03")
    tables, where = matchings_from(square)
    whole = f"w AS MATERIALIZED (SELECT {', '.join(f'{column_of(square, v)} AS m{v}' for v in range(4))} FROM {tables} WHERE {where})"
    ranked = "SELECT 0 AS part, *, row_number() OVER (PARTITION BY m0, m2, m1 ORDER BY m3) AS k FROM w UNION ALL SELECT 1, *, row_number() OVER (PARTITION BY m0, m2, m3 ORDER BY m1) FROM w"
    out["materialize_k"] = f"WITH {edges_sql('bulk')}, {whole} SELECT part, count(*)::BIGINT AS n, sum(m1)::BIGINT AS sum_m1, sum(m3)::BIGINT AS sum_m3 FROM ({ranked}) WHERE k <= 2 GROUP BY part"
    return out


ORACLES = all_oracles()
