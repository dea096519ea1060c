"""DuckDB SQL for the graph queries.

The oracles match without bounds and divide by the number of automorphisms, or
reduce mappings to distinct vertex sets; they share no logic with the engine beyond
the pattern's edges.
"""

from __future__ import annotations

from itertools import permutations

from .functions.pattern import CATALOG, Pattern, connected_patterns, known_name, parse

GRAPHS: dict[str, str] = {
    "copart_q45": "p AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS x FROM lineitem WHERE l_quantity >= 45), e0 AS (SELECT DISTINCT a.x AS u, b.x AS v FROM p a JOIN p b ON a.o = b.o AND a.x < b.x)",
    "copart_s2": "p AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS x FROM lineitem), e0 AS (SELECT a.x AS u, b.x AS v FROM p a JOIN p b ON a.o = b.o AND a.x < b.x GROUP BY 1, 2 HAVING count(*) >= 2)",
    "copart_all": "p AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS x FROM lineitem), e0 AS (SELECT DISTINCT a.x AS u, b.x AS v FROM p a JOIN p b ON a.o = b.o AND a.x < b.x)",
    "doc_lines": "t AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), p AS (SELECT DISTINCT doc_id AS x, line AS o FROM t WHERE length(line) >= 20), f AS (SELECT o FROM p GROUP BY o HAVING count(*) BETWEEN 2 AND 50), e0 AS (SELECT DISTINCT a.x AS u, b.x AS v FROM f JOIN p a ON a.o = f.o JOIN p b ON b.o = f.o AND a.x < b.x)",
    "doc_lines_all": "t AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), p AS (SELECT DISTINCT doc_id AS x, line AS o FROM t WHERE length(line) >= 20), e0 AS (SELECT DISTINCT a.x AS u, b.x AS v FROM p a JOIN p b ON a.o = b.o AND a.x < b.x)",
    "cust_supp": "e0 AS (SELECT DISTINCT least(c, s) AS u, greatest(c, s) AS v FROM (SELECT 2 * o_custkey AS c, 2 * l_suppkey + 1 AS s FROM orders JOIN lineitem ON o_orderkey = l_orderkey))",
    "cust_nation": "e0 AS (SELECT DISTINCT least(c, s) AS u, greatest(c, s) AS v FROM (SELECT CAST(2 * c_custkey AS BIGINT) AS c, CAST(2 * c_nationkey + 1 AS BIGINT) AS s FROM customer))",
    "user_chain": "q AS (SELECT lag(user_id) OVER (ORDER BY ts, user_id) AS a, user_id AS b FROM events), e0 AS (SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM q WHERE a IS NOT NULL AND a <> b)",
    "emb_knn": "w AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings), q AS (SELECT a.vec_id AS a, b.vec_id AS b, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(a.e, b.e) DESC, b.vec_id) AS r FROM w a JOIN w b ON a.vec_id <> b.vec_id), e0 AS (SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM q WHERE r <= 5)",
    "user_day": "p AS (SELECT DISTINCT date_trunc('day', ts) AS o, user_id AS x FROM events), e0 AS (SELECT DISTINCT a.x AS u, b.x AS v FROM p a JOIN p b ON a.o = b.o AND a.x < b.x)",
}


def graph(name: str) -> str:
    """WITH clause that defines e(u, v), the symmetric edges."""
    return f"WITH {GRAPHS[name]}, e AS MATERIALIZED (SELECT u, v FROM e0 UNION ALL SELECT v, u FROM e0), d AS MATERIALIZED (SELECT u AS x, count(*) AS degree FROM e GROUP BY u)"


def autos(p: Pattern) -> int:
    """Automorphisms by trying every permutation."""
    return sum(all(p.has(g[i], g[j]) for i, j in p.edges) for g in permutations(range(p.k)))


def matching(p: Pattern, induced: bool = True) -> str:
    """FROM ... WHERE of all mappings x0..x(k-1), without bounds."""
    order, placed = [0], {0}
    while len(order) < p.k:  # breadth first, most edges back first
        nxt = max((i for i in range(p.k) if i not in placed), key=lambda i: (sum(p.has(i, j) for j in placed), -i))
        order.append(nxt), placed.add(nxt)
    at: dict[int, str] = {}
    tables, where = [], []
    for n, i in enumerate(order[1:], 1):
        back = [j for j in order[:n] if p.has(i, j)]
        for m, j in enumerate(back):
            t = f"e{j}_{i}"
            on = ([f"{t}.u = {at[j]}"] if j in at else []) + ([f"{t}.v = {at[i]}"] if m else [])
            at.setdefault(j, f"{t}.u")
            at.setdefault(i, f"{t}.v")
            tables.append(f"JOIN e {t} ON {' AND '.join(on)}" if tables else f"FROM e {t}")
        for j in order[:n]:
            if not p.has(i, j):
                where.append(f"{at[i]} <> {at[j]}")
                if induced:
                    where.append(f"NOT EXISTS (SELECT 1 FROM e n WHERE n.u = {at[j]} AND n.v = {at[i]})")
    ids = ", ".join(f"{at[i]} AS x{i}" for i in range(p.k))
    return f"(SELECT {ids} {' '.join(tables)}" + (f" WHERE {' AND '.join(where)}" if where else "") + ")"


def count(g: str, pattern: str | Pattern, induced: bool = True) -> str:
    p = parse(pattern) if isinstance(pattern, str) else pattern
    return f"{graph(g)} SELECT count(*) // {autos(p)} AS cnt FROM {matching(p, induced)}"


def cliques(g: str, k: int) -> str:
    """Cliques of three or four vertices, each met once in ascending order of ids: without
    an order the matching of a dense graph has 24 times the rows."""
    edge = lambda x, y: f"EXISTS (SELECT 1 FROM s c WHERE c.u = {x} AND c.v = {y})"
    three = f"SELECT a.u, a.v, b.v AS w FROM s a JOIN s b ON b.u = a.v WHERE {edge('a.u', 'b.v')}"
    four = f"SELECT 1 FROM tri JOIN s a ON a.u = tri.w WHERE {edge('tri.u', 'a.v')} AND {edge('tri.v', 'a.v')}"
    return f"WITH {GRAPHS[g]}, s AS MATERIALIZED (SELECT u, v FROM e0), tri AS MATERIALIZED ({three}) SELECT count(*) AS cnt FROM {'tri' if k == 3 else f'({four})'}"


def listing(g: str, pattern: str) -> str:
    p = parse(pattern)
    xs = ", ".join(f"x{i}" for i in range(p.k))
    cols = ", ".join(f"s[{i + 1}] AS v{i}" for i in range(p.k))
    return f"{graph(g)} SELECT {cols} FROM (SELECT DISTINCT list_sort([{xs}]) AS s FROM {matching(p)})"


def automorphisms_in(g: str, pattern: str) -> str:
    """All mappings, without bounds: every instance under every automorphism."""
    p = parse(pattern)
    return f"{graph(g)} SELECT {', '.join(f'x{i} AS v{i}' for i in range(p.k))} FROM {matching(p)}"


def bounds_in(g: str, pattern: str, held: list[tuple[str, str]]) -> str:
    """The given bounds (upper, lower) of the labels in alphabetical order, with the ids
    that they compare in every mapping that keeps them."""
    p = parse(pattern)
    plan = levels(p, tuple(range(p.k)))
    pairs = [(ord(u) - 97, ord(w) - 97) for u, w in held]
    plan = [x | {"below": [u for u, w in pairs if w == i]} for i, x in enumerate(plan)]
    each = " UNION ALL ".join(f"SELECT '{a}' AS upper, '{b}' AS lower, x{u} AS high, x{w} AS low FROM m" for (a, b), (u, w) in zip(held, pairs))
    return f"{ranked(g)}, m AS MATERIALIZED {prefixes(plan, p.k)} {each}"


def per_vertex(g: str, pattern: str) -> str:
    p = parse(pattern)
    xs = ", ".join(f"x{i}" for i in range(p.k))
    return f"{graph(g)} SELECT vertex, count(*) // {autos(p)} AS cnt FROM (SELECT unnest([{xs}]) AS vertex FROM {matching(p)}) GROUP BY vertex"


def motifs(g: str, k: int) -> str:
    rows = " UNION ALL ".join(
        f"SELECT CAST({k} AS INTEGER) AS k, '{known_name(p)}' AS pattern, CAST({len(p.edges)} AS INTEGER) AS edges, CAST({autos(p)} AS BIGINT) AS autos, (SELECT count(*) // {autos(p)} FROM {matching(p)}) AS cnt"
        for p in connected_patterns(k)
    )
    return f"{graph(g)} {rows}"


def motif3(g: str) -> str:
    """By the identity: two-edge paths less three for each triangle."""
    return f"""{graph(g)}, tri AS (SELECT count(*) // 6 AS n FROM e a JOIN e b ON a.v = b.u JOIN e c ON c.u = b.v AND c.v = a.u),
two AS (SELECT CAST(coalesce(sum(degree * (degree - 1) // 2), 0) AS BIGINT) AS n FROM d)
SELECT CAST(3 AS INTEGER) AS k, 'wedge' AS pattern, CAST(2 AS INTEGER) AS edges, CAST(2 AS BIGINT) AS autos, two.n - 3 * tri.n AS cnt FROM two, tri
UNION ALL SELECT 3, 'triangle', 3, 6, tri.n FROM tri"""


def grid(g: str, pattern: str, root: bool) -> str:
    """Every cell of the ablation: the count, and mappings by the form's factor. ``root``
    says whether the chosen order starts with two labels that can be exchanged."""
    p = parse(pattern)
    n = autos(p)
    forms = ", ".join(f"('{f}', {x})" for f, x in (("none", n), ("root", n // 2 if root else n), ("full", 1), ("min", 1)))
    return f"{graph(g)}, c AS (SELECT count(*) // {n} AS n FROM {matching(p)}) SELECT f.bounds, o.oriented, s.bounded_scan, c.n * f.factor AS mappings, c.n AS cnt FROM c, (VALUES {forms}) f(bounds, factor), (VALUES (false), (true)) o(oriented), (VALUES (false), (true)) s(bounded_scan)"


def redundancy(g: str, pattern: str, root: bool) -> str:
    """Mappings of each form; ``root`` as in ``grid``, for the baseline's order."""
    p = parse(pattern)
    n = autos(p)
    forms = f"('none', {n}), ('root', {n // 2 if root else n}), ('full', 1), ('min', 1)"
    return f"{graph(g)}, c AS (SELECT count(*) // {n} AS n FROM {matching(p)}) SELECT f.bounds, c.n * f.factor AS mappings, c.n AS cnt, CAST(f.factor AS BIGINT) AS factor FROM c, (VALUES {forms}) f(bounds, factor)"


# Work measures, from the definitions: bounds by trying every permutation, prefixes as
# joins over the ranked edges q(src, dst).

RANKED = "r AS MATERIALIZED (SELECT x, row_number() OVER (ORDER BY {by}x) - 1 AS id FROM d), q AS MATERIALIZED (SELECT a.id AS src, b.id AS dst FROM e JOIN r a ON a.x = e.u JOIN r b ON b.x = e.v), l AS MATERIALIZED (SELECT src, list(dst) AS l FROM q GROUP BY src)"


def ranked(g: str, oriented: bool = True) -> str:
    return f"{graph(g)}, {RANKED.format(by='degree DESC, ' if oriented else '')}"


def levels(p: Pattern, order: tuple[int, ...], form: str = "min") -> list[dict]:
    """What each label of an order is joined to, kept apart from, and bounded by."""
    group = [g for g in permutations(range(p.k)) if all(p.has(g[i], g[j]) for i, j in p.edges)]
    place, full = {x: i for i, x in enumerate(order)}, []
    for x in order:
        full += [(place[x], place[y]) for y in {g[x] for g in group} if y != x]
        group = [g for g in group if g[x] == x]
    out = []
    for i in range(p.k):
        near = [j for j in range(i) if p.has(order[i], order[j])]
        above = sorted(u for u, w in full if w == i)
        out.append({"near": near, "apart": [j for j in range(i) if j not in near], "above": above, "below": above if form == "full" else above[-1:]})
    return out


def prefixes(plan: list[dict], n: int) -> str:
    """All prefixes of n labels: x0..x(n-1)."""
    tables, where = ["r r0"], []
    at = lambda i: f"q{i}.dst" if i else "r0.id"
    for i, x in enumerate(plan[1:n], 1):
        tables.append(f"JOIN q q{i} ON q{i}.src = {at(x['near'][0])}")
        where += [f"EXISTS (SELECT 1 FROM q c WHERE c.src = {at(j)} AND c.dst = {at(i)})" for j in x["near"][1:]]
        where += [f"NOT EXISTS (SELECT 1 FROM q c WHERE c.src = {at(j)} AND c.dst = {at(i)})" for j in x["apart"]]
        where += [f"{at(i)} < {at(j)}" for j in x["below"]] + [f"{at(i)} <> {at(j)}" for j in x["apart"]]
    return f"(SELECT {', '.join(f'{at(i)} AS x{i}' for i in range(n))} FROM {' '.join(tables)}" + (f" WHERE {' AND '.join(where)}" if where else "") + ")"


def work_rows(plan: list[dict], half: bool = True) -> str:
    """level, candidates, kept, checks of the joins: the first list that a bound cuts, or
    else the first one, gives the candidates."""
    rows = ["SELECT CAST(0 AS INTEGER) AS level, count(*) AS candidates, count(*) AS kept, CAST(0 AS BIGINT) AS checks FROM r"]
    for i, x in enumerate(plan[1:], 1):
        cut = next((j for j in x["near"] if j in x["above"]), None)
        first = x["near"][0] if cut is None else cut
        met = f"(SELECT count(*) FROM {prefixes(plan, i)} p JOIN q ON q.src = p.x{first}" + (" AND q.dst < q.src" if half and cut is not None else "") + ")"
        rows.append(f"SELECT {i}, {met}, (SELECT count(*) FROM {prefixes(plan, i + 1)}), {met} * {len(x['below'])}")
    return " UNION ALL ".join(rows)


def touched_sum(plan: list[dict], bounded: bool = True) -> str:
    """The list elements that nested loops read: every list a level intersects, and every
    list it subtracts from what is not yet empty; up to the bound, or whole."""
    parts = []
    for i, x in enumerate(plan[1:], 1):
        cap = f"p.x{x['below'][0]}" if x["below"] else None
        cut = lambda c, on=cap: f"list_filter({c}, lambda z: z < {on})" if on else c
        seen = (lambda c: cut(c)) if bounded else (lambda c: c)
        lists = {j: f"l{j}.l" for j in x["near"] + x["apart"]}
        both = cut(lists[x["near"][0]])
        for j in x["near"][1:]:
            both = f"list_intersect({both}, {lists[j]})"
        cost = [f"len({seen(lists[j])})" for j in x["near"]]
        for j in x["apart"]:
            cost.append(f"CASE WHEN len({both}) > 0 THEN len({seen(lists[j])}) ELSE 0 END")
            both = f"list_filter({both}, lambda z: NOT list_contains({lists[j]}, z))"
        joins = " ".join(f"JOIN l l{j} ON l{j}.src = p.x{j}" for j in lists)
        parts.append(f"coalesce((SELECT sum({' + '.join(cost)}) FROM {prefixes(plan, i)} p {joins}), 0)")
    return f"CAST({' + '.join(parts)} AS BIGINT)"


def classes(p: Pattern) -> list[tuple[int, ...]]:
    """The least order of each class of valid orders, by trying every permutation."""
    group = [g for g in permutations(range(p.k)) if all(p.has(g[i], g[j]) for i, j in p.edges)]
    valid = [o for o in permutations(range(p.k)) if all(any(p.has(o[i], x) for x in o[:i]) for i in range(1, p.k))]
    return sorted({min(tuple(g[x] for x in o) for g in group) for o in valid})


def expected_cost(p: Pattern, order: tuple[int, ...], n: int = 1000, edge: float = 0.005) -> float:
    """The model's cost of an order; the chance of the bounds by trying every ranking."""
    plan, total, entries = levels(p, order), 0.0, 1.0
    for i, x in enumerate(plan):
        entries *= n * edge ** len(x["near"]) * (1 - edge) ** len(x["apart"])
        ranks = list(permutations(range(i)))
        total += entries * sum(all(t[j] > t[m] for m in range(i) for j in plan[m]["below"]) for t in ranks) / len(ranks)
    return total


def letters(order: tuple[int, ...]) -> str:
    return "".join("abcdefg"[x] for x in order)


def orders_table(pattern: str) -> str:
    p = parse(pattern)
    rows = sorted((round(expected_cost(p, o), 2), o) for o in classes(p))
    bound = lambda o: ",".join(f"{letters((o[x['below'][0]],))}>{letters((o[i],))}" for i, x in enumerate(levels(p, o)) if x["below"])
    return values([(i + 1, letters(o), c, bound(o)) for i, (c, o) in enumerate(rows)], {"rnk": "INTEGER", "ord": "VARCHAR", "cost": "DOUBLE", "bounds": "VARCHAR"})


def order_work(g: str, pattern: str) -> str:
    """ord, predicted, touched, mappings of every class of orders."""
    p = parse(pattern)
    rows = [
        f"SELECT '{letters(o)}' AS ord, CAST({round(expected_cost(p, o), 2)!r} AS DOUBLE) AS predicted, {touched_sum(plan)} AS touched, (SELECT count(*) FROM {prefixes(plan, p.k)}) AS mappings"
        for o in classes(p) for plan in [levels(p, o)]
    ]
    return f"{ranked(g)} {' UNION ALL '.join(rows)}"


def order_fit(g: str, pattern: str) -> str:
    return f"SELECT count(*) AS n, round(corr(predicted, touched) ** 2, 6) AS r2, round(corr(ln(predicted), ln(touched)) ** 2, 6) AS r2_log FROM ({order_work(g, pattern)})"


def gain_rows(g: str, patterns: dict[str, str]) -> str:
    """Mappings and list elements of every pattern (name: order), with and without the
    renumbering and the bounded scan. The two numberings need a graph clause each."""
    parts = []
    for oriented in (False, True):
        inner = " UNION ALL ".join(
            f"SELECT '{x}' AS pattern, {str(oriented).lower()} AS oriented, {str(scan).lower()} AS bounded_scan, (SELECT count(*) FROM {prefixes(plan, len(plan))}) AS mappings, {touched_sum(plan, scan)} AS touched"
            for x, o in patterns.items() for plan in [levels(parse(x), tuple(ord(c) - 97 for c in o))] for scan in (False, True)
        )
        parts.append(f"SELECT * FROM ({ranked(g, oriented)} {inner})")
    return " UNION ALL ".join(parts)


def values(rows: list[tuple], columns: dict[str, str]) -> str:
    """Literal rows with typed columns."""
    lit = lambda x: "NULL" if x is None else f"'{x}'" if isinstance(x, str) else repr(x)
    body = ", ".join("(" + ", ".join(map(lit, r)) + ")" for r in rows)
    cast = ", ".join(f"CAST({c} AS {t}) AS {c}" for c, t in columns.items())
    return f"SELECT {cast} FROM (VALUES {body}) t({', '.join(columns)})"


# Pattern, labels, automorphisms, valid orders, distinct orders, least
# and largest cost over distinct orders on the reference model graph.
CENSUS = [
    ("triangle", 3, 6, 6, 1, 6062.5, 6062.5),
    ("wedge", 3, 2, 4, 2, 30875.0, 30875.0),
    ("rectangle", 4, 8, 16, 2, 18540.63, 18643.76),
    ("tailed_triangle", 4, 2, 14, 7, 6371.88, 31493.77),
    ("diamond", 4, 4, 20, 5, 6064.05, 30876.55),
    ("clique_4", 4, 24, 24, 1, 6062.5, 6062.5),
    ("pentagon", 5, 10, 40, 4, 39340.85, 60244.2),
    ("house", 5, 2, 60, 30, 6379.54, 154024.67),
    ("bow_tie", 5, 8, 56, 7, 6376.99, 31189.49),
    ("hexagon", 6, 12, 96, 8, 116263.82, 214090.15),
    ("prism", 6, 12, 360, 30, 6167.54, 59486.12),
    ("near_clique_7", 7, 240, 4800, 20, 6062.5, 30876.55),
]
CENSUS_COLUMNS = {"pattern": "VARCHAR", "k": "INTEGER", "autos": "BIGINT", "valid": "BIGINT", "distinct_orders": "BIGINT", "best": "DOUBLE", "worst": "DOUBLE"}
# Connected patterns of k labels; their valid and distinct orders.
TOTALS = [(3, 2), (4, 6), (5, 21), (6, 112), (7, 853)]
ORDER_TOTALS = [(3, 10, 3), (4, 94, 21), (5, 1314, 315)]
MORE_TOTALS = [(6, 34182, 9765)]

assert all(name in CATALOG for name, *_ in CENSUS)
