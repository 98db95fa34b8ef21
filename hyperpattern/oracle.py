"""DuckDB SQL for the engine's results, by formulations that the engine doesn't use: intersections of all subsets, or vertex mappings."""

from __future__ import annotations

from itertools import combinations

from .carriers import edges_sql
from .pattern import PatternGraph


def _list(values: list[str]) -> str:
    return "[" + ", ".join(f"'{v}'" for v in values) + "]::VARCHAR[]"


def _candidates(p: PatternGraph, name: str, simple: bool) -> str:
    ctes = [f"edges AS ({edges_sql(name, simple)})"]
    for q, e in enumerate(p.edges):
        named = f" AND elabel = '{p.elabels[q]}'" if p.elabels else ""
        ctes.append(f"c{q} AS (SELECT e AS m{q}, tagged AS x{q} FROM edges WHERE labels = {_list(p.signature(e))}{named})")
    return "WITH " + ", ".join(ctes)


def by_subsets(p: PatternGraph, name: str, simple: bool = True) -> str:
    """The product of the candidates; every subset of two or more edges meets in vertices of the right labels."""
    joins, seen = "c0", []
    for q in range(p.size):
        tests = []
        for n in range(1, q + 1):
            for s in combinations(range(q), n):
                common = f"x{q}"
                for i in s:
                    common = f"list_intersect({common}, x{i})"
                want = p.signature(set.intersection(*(set(p.edges[i]) for i in (*s, q))))
                tests.append(f"list_sort(list_transform({common}, lambda z: split_part(z, '\t', 2))) = {_list(want)}")
        if not simple:
            tests += [f"m{q} <> m{i}" for i in range(q)]
        seen.append(f"m{q}")
        if q:
            joins = f"(SELECT * FROM {joins} JOIN c{q} ON {' AND '.join(tests)})"
    return f"{_candidates(p, name, simple)} SELECT {', '.join(seen)} FROM {joins}"


def by_vertices(p: PatternGraph, name: str, arity: bool = True) -> str:
    """One relation for each vertex of each query edge; equal vertices where the query shares them, different ones elsewhere. arity False: data edges may be larger than the query's, and are all different."""
    rows = f"WITH edges AS ({edges_sql(name)}), inc AS (SELECT e, len(members) AS arity, unnest(members) AS v, unnest(tagged) AS t, FROM edges), i AS (SELECT e, arity, split_part(t, '\t', 1) AS v, split_part(t, '\t', 2) AS l FROM inc)"
    tables, tests, place = [], [], {}
    for q, e in enumerate(p.edges):
        for k, u in enumerate(e):
            name_ = f"t{q}_{k}"
            tables.append(f"i {name_}")
            tests += [f"{name_}.arity = {len(e)}"] * arity + [f"{name_}.l = '{p.label[u]}'"]
            if k:
                tests.append(f"{name_}.e = t{q}_0.e")
            if u in place:
                tests.append(f"{name_}.v = {place[u]}.v")
            else:
                tests += [f"{name_}.v <> {o}.v" for o in place.values()]
                place[u] = name_
    if not arity:
        tests += [f"t{a}_0.e <> t{b}_0.e" for a, b in combinations(range(p.size), 2)]
    columns = ", ".join(f"t{q}_0.e AS m{q}" for q in range(p.size))
    return f"{rows} SELECT DISTINCT {columns} FROM {', '.join(tables)} WHERE {' AND '.join(tests)}"


def by_walk(name: str, size: int, n: int, seed: int = 0) -> str:
    """embedding_id, q, f of the first of n walks as a query: its edges are found by the walk's own SQL, and intersections of all subsets of candidates are compared with those of the walk's edges."""
    sql = f"WITH edges AS ({edges_sql(name)}), walk AS ({walks(name, size, n, seed)}), chosen AS (SELECT step, e FROM walk WHERE query = (SELECT min(query) FROM walk))"
    for q in range(size):
        sql += f", c{q} AS (SELECT d.e AS m{q}, d.tagged AS x{q}, o.tagged AS y{q} FROM chosen JOIN edges o ON o.e = chosen.e AND step = {q} JOIN edges d ON d.labels = o.labels AND d.elabel IS NOT DISTINCT FROM o.elabel)"
    joins = "c0"
    for q in range(1, size):
        tests = []
        for k in range(1, q + 1):
            for s in combinations(range(q), k):
                x, y = f"x{q}", f"y{q}"
                for i in s:
                    x, y = f"list_intersect({x}, x{i})", f"list_intersect({y}, y{i})"
                tests.append(f"list_sort(list_transform({x}, lambda z: split_part(z, '\t', 2))) = list_sort(list_transform({y}, lambda z: split_part(z, '\t', 2)))")
        joins = f"(SELECT * FROM {joins} JOIN c{q} ON {' AND '.join(tests)})"
    ids = ", ".join(f"m{q}" for q in range(size))
    parts = " UNION ALL ".join(f"SELECT concat_ws('|', {ids}) AS embedding_id, {q} AS q, m{q} AS f FROM found" for q in range(size))
    return f"{sql}, found AS (SELECT {ids} FROM {joins}) {parts}"


def stats(name: str) -> str:
    return f"WITH edges AS ({edges_sql(name)}), v AS (SELECT DISTINCT unnest(tagged) AS t FROM edges), a AS (SELECT count(DISTINCT split_part(t, '\t', 1)) AS n_vertices, count(DISTINCT split_part(t, '\t', 2)) AS n_labels FROM v), b AS (SELECT count(*) AS n_edges, CAST(max(len(members)) AS BIGINT) AS max_arity, round(avg(len(members)), 6) AS avg_arity, count(DISTINCT labels) AS n_signatures FROM edges) SELECT n_vertices, n_edges, n_labels, max_arity, avg_arity, n_signatures FROM a, b"


def signature_partitions(name: str) -> str:
    return f"WITH edges AS ({edges_sql(name)}) SELECT array_to_string(labels, '|') AS sig, count(*) AS n_edges FROM edges GROUP BY labels"


def edge_adjacency(name: str) -> str:
    return f"WITH edges AS ({edges_sql(name)}), i AS (SELECT e, unnest(members) AS v FROM edges) SELECT x.e AS a, y.e AS b, count(*) AS n_shared FROM i x JOIN i y ON x.v = y.v AND x.e < y.e GROUP BY x.e, y.e"


def init_candidates(p: PatternGraph, name: str) -> str:
    parts = " UNION ALL ".join(f"SELECT {q} AS q, m{q} AS f FROM c{q}" for q in range(p.size))
    return f"{_candidates(p, name, True)} {parts}"


def _connections(p: PatternGraph) -> list[str]:
    return [f"SELECT {a} AS q, m{a} AS f, {b} AS q2, m{b} AS f2 FROM c{a} JOIN c{b} ON m{a} <> m{b} AND list_sort(list_transform(list_intersect(x{a}, x{b}), lambda z: split_part(z, '\t', 2))) = {_list(s)}" for (a, b), s in p.overlaps.items()]


def connections(p: PatternGraph, name: str) -> str:
    half = " UNION ALL ".join(_connections(p))
    return f"{_candidates(p, name, True)}, h AS ({half}) SELECT q, f, q2, f2 FROM h UNION ALL SELECT q2, f2, q, f FROM h"


def filtered_candidates(p: PatternGraph, name: str, rounds: int = 6) -> str:
    """The deletion rule unrolled `rounds` times, at least as often as the data needs."""
    half = " UNION ALL ".join(_connections(p))
    parts = " UNION ALL ".join(f"SELECT {q} AS q, m{q} AS f FROM c{q}" for q in range(p.size))
    sql = f"{_candidates(p, name, True)}, h AS ({half}), k AS (SELECT q, f, q2, f2 FROM h UNION ALL SELECT q2, f2, q, f FROM h), s0 AS ({parts})"
    degree = " ".join(f"WHEN {q} THEN {p.adjacent[q].bit_count()}" for q in range(p.size))
    for r in range(rounds):
        sql += f", s{r + 1} AS (SELECT s.q, s.f FROM s{r} s LEFT JOIN (SELECT k.q, k.f, count(DISTINCT k.q2) AS n FROM k JOIN s{r} o ON o.q = k.q2 AND o.f = k.f2 GROUP BY k.q, k.f) d ON d.q = s.q AND d.f = s.f WHERE coalesce(d.n, 0) = CASE s.q {degree} END)"
    return f"{sql} SELECT q, f FROM s{rounds}"


def walks(name: str, size: int, n: int, seed: int = 0) -> str:
    """Each step takes the least md5 of what the walk reaches."""
    pick = lambda step, f: f"min_by({f}, struct_pack(a := md5(concat_ws('|', '{seed}', query, '{step}', {f})), b := {f}))"
    sql = f"WITH edges AS ({edges_sql(name)}), i AS (SELECT e, unnest(members) AS v FROM edges), q AS (SELECT range AS query FROM range({n})), w0 AS (SELECT query, 0 AS step, {pick(0, 'e')} AS e FROM q, edges GROUP BY query)"
    for s in range(1, size):
        sql += f", r{s} AS (SELECT DISTINCT w.query, i2.e AS e FROM w{s - 1} w JOIN i i1 ON i1.e = w.e JOIN i i2 ON i2.v = i1.v WHERE NOT EXISTS (SELECT 1 FROM w{s - 1} o WHERE o.query = w.query AND o.e = i2.e)), w{s} AS (SELECT * FROM w{s - 1} UNION ALL SELECT query, {s} AS step, {pick(s, 'e')} AS e FROM r{s} GROUP BY query)"
    return f"{sql} SELECT query, step, e FROM w{size - 1} WHERE query IN (SELECT query FROM w{size - 1} GROUP BY query HAVING count(*) = {size})"
