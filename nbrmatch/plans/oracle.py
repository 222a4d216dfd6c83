"""SQL for DuckDB that says what the queries of the catalogue return, from the tables alone.

Graph views, neighbourhood features and filters are written out as common table expressions. Filters by code are stated
by degree and counts (equal degree asks for equal counts), which shares no code with the engine's integers.
"""

from __future__ import annotations

from ..operators.pattern import Pattern

SPACE = 10**14

GRAPHS = {
    "T": (
        f"""SELECT {SPACE}+c_custkey AS vid, 'C:'||c_mktsegment AS vlabel FROM customer
            UNION ALL SELECT {2 * SPACE}+o_orderkey, 'O:'||o_orderpriority FROM orders
            UNION ALL SELECT {3 * SPACE}+p_partkey, 'P:'||p_type FROM part
            UNION ALL SELECT {4 * SPACE}+s_suppkey, 'S:'||r_name FROM supplier JOIN nation ON s_nationkey=n_nationkey JOIN region ON n_regionkey=r_regionkey""",
        f"""SELECT {SPACE}+o_custkey AS src, {2 * SPACE}+o_orderkey AS dst, 'placed' AS elabel FROM orders
            UNION ALL SELECT DISTINCT {2 * SPACE}+l_orderkey, {3 * SPACE}+l_partkey, 'contains' FROM lineitem
            UNION ALL SELECT DISTINCT {2 * SPACE}+l_orderkey, {4 * SPACE}+l_suppkey, 'sourced' FROM lineitem
            UNION ALL SELECT DISTINCT {3 * SPACE}+l_partkey, {4 * SPACE}+l_suppkey, 'supplies' FROM lineitem""",
    ),
    "D": (
        f"SELECT {3 * SPACE}+p_partkey AS vid, p_brand AS vlabel FROM part UNION ALL SELECT {4 * SPACE}+s_suppkey, 'N'||s_nationkey FROM supplier",
        f"SELECT {3 * SPACE}+l_partkey AS src, {4 * SPACE}+l_suppkey AS dst, min(l_returnflag) AS elabel FROM lineitem GROUP BY 1, 2",
    ),
    "Y": (
        f"SELECT {3 * SPACE}+p_partkey AS vid, p_brand||'/'||(p_size%3) AS vlabel FROM part",
        f"SELECT DISTINCT {3 * SPACE}+a.l_partkey AS src, {3 * SPACE}+b.l_partkey AS dst, NULL::VARCHAR AS elabel FROM lineitem a JOIN lineitem b ON a.l_orderkey=b.l_orderkey AND a.l_partkey<b.l_partkey WHERE a.l_returnflag='R' AND b.l_returnflag='R'",
    ),
    "H": (
        f"SELECT {3 * SPACE}+p_partkey AS vid, p_brand||'/'||p_type AS vlabel FROM part UNION ALL SELECT {2 * SPACE}+o_orderkey, 'N'||c_nationkey||'/'||c_mktsegment FROM orders JOIN customer ON o_custkey=c_custkey",
        f"SELECT DISTINCT {3 * SPACE}+l_partkey AS src, {2 * SPACE}+l_orderkey AS dst, NULL::VARCHAR AS elabel FROM lineitem",
    ),
    "E": (
        f"SELECT {5 * SPACE}+event_id AS vid, event_type AS vlabel FROM events",
        f"""SELECT {5 * SPACE}+event_id AS src, {5 * SPACE}+nxt AS dst, CASE WHEN gap < 3600000000 THEN '<1h' WHEN gap < 86400000000 THEN '<1d' ELSE '>=1d' END AS elabel
            FROM (SELECT event_id, lead(event_id) OVER w AS nxt, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS gap FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE nxt IS NOT NULL""",
    ),
}


def text(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def graph(name: str, directed: bool = False) -> str:
    """CTEs v, e and adj of a graph view."""
    v, e = GRAPHS[name]
    out, back = ("O", "I") if directed else ("B", "B")
    return f"v AS ({v}), e AS ({e}), adj AS (SELECT src, dst, elabel, '{out}' AS dir FROM e UNION ALL SELECT dst, src, elabel, '{back}' FROM e)"


def triple(q: Pattern, a: str = "s.vlabel", b: str = "d.vlabel") -> str:
    tests = []
    for x, y, e in sorted(q.triples(), key=str):
        more = "" if e is None else f" AND a.elabel={text(e)}"
        one = f"({a}={text(x)} AND {b}={text(y)}{more}" + (" AND a.dir='O')" if q.directed else ")")
        tests.append(one)
        if q.directed:
            tests.append(f"({a}={text(y)} AND {b}={text(x)}{more} AND a.dir='I')")
    return " OR ".join(tests) or "false"


def pruned(q: Pattern) -> str:
    """CTEs lv and la: vertices with a pattern label, edges with a pattern triple."""
    labels = ", ".join(map(text, q.labels))
    return f"lv AS (SELECT * FROM v WHERE vlabel IN ({labels})), la AS (SELECT a.*, d.vlabel AS dlabel FROM adj a JOIN lv s ON s.vid=a.src JOIN lv d ON d.vid=a.dst WHERE {triple(q)})"


def counts(q: Pattern, vertices: str = "lv", edges: str = "la", name: str = "f", elabels: list[str] | None = None) -> str:
    """CTE of features: x1..xk, pdeg; with edge labels also e1.., or i1.. and o1.. for directed patterns."""
    xs = ", ".join(f"count(*) FILTER (WHERE a.dlabel={text(n)}) AS x{k}" for k, n in enumerate(q.labels, 1))
    for k, n in enumerate(elabels or [], 1):
        for kind in "io" if q.directed else "e":
            way = f" AND a.dir='{kind.upper()}'" if q.directed else ""
            xs += f", count(*) FILTER (WHERE a.elabel={text(n)}{way}) AS {kind}{k}"
    return f"{name} AS (SELECT v.vid, v.vlabel, {xs}, count(a.dst) AS pdeg FROM {vertices} v LEFT JOIN {edges} a ON a.src=v.vid GROUP BY 1, 2)"


def mnd(name: str = "m") -> str:
    return f"{name} AS (SELECT f.*, coalesce(n.mnd, 0) AS mnd FROM f LEFT JOIN (SELECT a.src, max(g.pdeg) AS mnd FROM la a JOIN f g ON g.vid=a.dst GROUP BY 1) n ON n.src=f.vid)"


def edge_test(q: Pattern, u: str, elabels: list[str]) -> str:
    """Larger degree (in each direction), or all counts equal: by neighbour label, and by edge label and direction."""
    want = {kind: [sum(e == n and (kind == "e" and u in (a, b) or kind == "i" and b == u or kind == "o" and a == u) for a, b, e in q.edges) for n in elabels] for kind in ("io" if q.directed else "e")}
    equal = " AND ".join([*(f"x{k}={n}" for k, n in enumerate(q.vector(u), 1)), *(f"{kind}{k}={n}" for kind, ns in want.items() for k, n in enumerate(ns, 1))])
    more = "".join(f" AND {'+'.join(f'{kind}{k}' for k in range(1, len(ns) + 1))}>={sum(ns)}" for kind, ns in want.items()) if q.directed else ""
    return f"vlabel={text(q.vertices[u])} AND ((pdeg>{q.pdeg(u)}{more}) OR (pdeg={q.pdeg(u)} AND {equal}))"


def test(q: Pattern, u: str, kind: str, elabels: list[str] | None = None) -> str:
    if kind == "edges":
        return edge_test(q, u, elabels)
    x = q.vector(u)
    d = q.pdeg(u)
    is_label = f"vlabel={text(q.vertices[u])}"
    at_least = " AND ".join([f"x{k}>={n}" for k, n in enumerate(x, 1) if n] or ["true"])
    equal = " AND ".join(f"x{k}={n}" for k, n in enumerate(x, 1))
    sums = ["0", *(("+".join(f"x{i}" for i in range(1, k + 1))) for k in range(1, len(x) + 1))]
    # Codes in order: of equal sums the vector with the larger prefix sums, compared from the last but one, is larger.
    lex, tied = "", ""
    for k in range(len(x) - 1, 0, -1):
        s = sum(x[:k])
        lex += (" OR " if lex else "") + f"({tied}({sums[k]})>{s})"
        tied += f"({sums[k]})={s} AND "
    lemma = f"({lex} OR ({equal}))" if lex else "true"
    return {
        "label": is_label,
        "degree": f"{is_label} AND pdeg>={d}",
        "mnd": f"{is_label} AND pdeg>={d} AND mnd>={q.mnd(u)}",
        "nlf": f"{is_label} AND {at_least}",
        "mnd_nlf": f"{is_label} AND pdeg>={d} AND mnd>={q.mnd(u)} AND {at_least}",
        "strict": f"{is_label} AND (pdeg>{d} OR (pdeg={d} AND {equal}))",
        "lemma": f"{is_label} AND (pdeg>{d} OR (pdeg={d} AND {lemma}))",
    }[kind]


def candidates(q: Pattern, kind: str, source: str = "f") -> str:
    return " UNION ALL ".join(f"SELECT {text(u)} AS u, vid FROM {source} WHERE {test(q, u, kind)}" for u in sorted(q.vertices))


def some(q: Pattern, kind: str, elabels: list[str] | None = None) -> str:
    return " OR ".join(f"({test(q, u, kind, elabels)})" for u in sorted(q.vertices))


def peel(q: Pattern, rounds: int, kind: str = "strict", elabels: list[str] | None = None) -> str:
    """CTEs f0, k0, a0, f1, ...: features, kept vertices and edges of each round, unrolled."""
    parts, vertices, edges = [], "lv", "la"
    for r in range(rounds):
        parts.append(counts(q, vertices, edges, f"f{r}", elabels))
        parts.append(f"k{r} AS (SELECT vid, vlabel FROM f{r} WHERE {some(q, kind, elabels)})")
        parts.append(f"a{r} AS (SELECT a.* FROM {edges} a JOIN k{r} s ON s.vid=a.src JOIN k{r} d ON d.vid=a.dst)")
        vertices, edges = f"k{r}", f"a{r}"
    return ", ".join(parts)


def with_(*parts: str) -> str:
    return "WITH " + ", ".join(parts) + " "


def features(name: str, q: Pattern) -> str:
    return with_(graph(name, q.directed), pruned(q), counts(q))


def embeddings(name: str, q: Pattern, select: str | None = None) -> str:
    """The pattern as an n-way join."""
    names = sorted(q.vertices)
    where = [f"v_{u}.vlabel={text(q.vertices[u])}" for u in names]
    tables = [f"v v_{u}" for u in names]
    for k, (a, b, e) in enumerate(q.edges):
        tables.append(f"adj e{k}")
        where += [f"e{k}.src=v_{a}.vid", f"e{k}.dst=v_{b}.vid"]
        if q.directed:
            where.append(f"e{k}.dir='O'")
        if e is not None:
            where.append(f"e{k}.elabel={text(e)}")
    where += [f"v_{a}.vid<>v_{b}.vid" for i, a in enumerate(names) for b in names[:i] if q.vertices[a] == q.vertices[b]]
    columns = select or "DISTINCT " + ", ".join(f"v_{u}.vid AS m_{u}" for u in names)
    return with_(graph(name, q.directed)) + f"SELECT {columns} FROM {', '.join(tables)} WHERE {' AND '.join(where)}"
