"""SQL of the derived graphs and of the measures over them, for comparison."""

from __future__ import annotations

from ..operators import hashing, peel

_KEYED = """d AS (SELECT key, row_number() OVER (ORDER BY key) AS id FROM (SELECT a AS key FROM k UNION SELECT b FROM k)),
e AS MATERIALIZED (SELECT DISTINCT least(x.id, y.id) AS src, greatest(x.id, y.id) AS dst FROM k JOIN d x ON x.key = a JOIN d y ON y.key = b WHERE x.id <> y.id)"""
_SELF = "e AS MATERIALIZED (SELECT DISTINCT x.v AS src, y.v AS dst FROM x JOIN x y ON x.k = y.k AND x.v < y.v)"
_SHARED = """l0 AS (SELECT DISTINCT doc_id AS v, line AS k FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20),
x AS (SELECT v, k, row_number() OVER (PARTITION BY k ORDER BY v) AS r FROM l0)"""
_NEXT = "FROM x JOIN x y ON x.k = y.k AND y.r BETWEEN x.r + 1 AND x.r + 8"
_LO = "lineitem JOIN orders ON l_orderkey = o_orderkey"

EDGES = {
    "tripartite": f"""x AS (SELECT DISTINCT o_custkey * 3 AS c, l_partkey * 3 + 1 AS p, l_suppkey * 3 + 2 AS s FROM {_LO}),
e AS MATERIALIZED (SELECT least(c, p) AS src, greatest(c, p) AS dst FROM x UNION SELECT least(c, s), greatest(c, s) FROM x UNION SELECT least(p, s), greatest(p, s) FROM x)""",
    "custpart": f"e AS MATERIALIZED (SELECT DISTINCT least(o_custkey * 3, l_partkey * 3 + 1) AS src, greatest(o_custkey * 3, l_partkey * 3 + 1) AS dst FROM {_LO})",
    "copurchase": f"x AS (SELECT DISTINCT l_orderkey AS k, l_partkey AS v FROM lineitem), {_SELF}",
    "cosupply": f"x AS (SELECT DISTINCT l_orderkey AS k, l_suppkey AS v FROM lineitem), {_SELF}",
    "copart30": f"""x AS (SELECT DISTINCT l_partkey AS k, o_custkey AS v, CAST(o_orderdate AS DATE) AS t FROM {_LO}),
e AS MATERIALIZED (SELECT DISTINCT x.v AS src, y.v AS dst FROM x JOIN x y ON x.k = y.k AND x.v < y.v AND abs(date_diff('day', x.t, y.t)) <= 30)""",
    "corun": """x AS (SELECT DISTINCT event_type AS k, user_id AS v, epoch_us(ts) AS t FROM events),
e AS MATERIALIZED (SELECT DISTINCT least(x.v, y.v) AS src, greatest(x.v, y.v) AS dst FROM x JOIN x y ON x.k = y.k AND x.v <> y.v AND y.t BETWEEN x.t AND x.t + 60000000)""",
    "trade": f"""e AS MATERIALIZED (SELECT DISTINCT CAST(least(c_nationkey, s_nationkey) AS BIGINT) AS src, CAST(greatest(c_nationkey, s_nationkey) AS BIGINT) AS dst
FROM {_LO} JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey WHERE c_nationkey <> s_nationkey)""",
    "vecsim": """v AS (SELECT vec_id, [CAST(z AS DOUBLE) FOR z IN embedding] AS q FROM embeddings),
e AS MATERIALIZED (SELECT DISTINCT x.vec_id AS src, y.vec_id AS dst FROM v x JOIN v y ON x.vec_id < y.vec_id WHERE list_cosine_similarity(x.q, y.q) >= 0.3)""",
    "lexical": f"""w AS (SELECT [lower(x) FOR x IN string_split_regex(text, '[^A-Za-z]+') IF x <> ''] AS w FROM conversations),
k AS (SELECT a, b FROM (SELECT w[i] AS a, w[i + 1] AS b FROM (SELECT w, unnest(range(1, len(w))) AS i FROM w)) WHERE a <> b), {_KEYED}""",
    "sharedline": f"{_SHARED}, e AS MATERIALIZED (SELECT DISTINCT x.v AS src, y.v AS dst {_NEXT})",
    "quality": f"""{_SHARED}, q0 AS (SELECT DISTINCT doc_id FROM labels WHERE quality = 1),
e AS MATERIALIZED (SELECT DISTINCT x.v AS src, y.v AS dst {_NEXT} WHERE x.v IN (SELECT doc_id FROM q0) AND y.v IN (SELECT doc_id FROM q0))""",
    "benchhit": """l0 AS (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 20),
b AS (SELECT DISTINCT item_id, line FROM (SELECT item_id, unnest(string_split(text, chr(10))) AS line FROM benchmark) WHERE length(line) >= 20),
e AS MATERIALIZED (SELECT DISTINCT least(doc_id * 2, item_id * 2 + 1) AS src, greatest(doc_id * 2, item_id * 2 + 1) AS dst FROM l0 JOIN b ON l0.line = b.line)""",
    "hyperlink": f"k AS (SELECT 'page ' || page_id AS a, 'href ' || unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS b FROM pages), {_KEYED}",
    "geo": """e AS MATERIALIZED (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (
SELECT CAST(n_regionkey AS BIGINT) * 4 AS a, CAST(n_nationkey AS BIGINT) * 4 + 1 AS b FROM nation
UNION ALL SELECT CAST(c_nationkey AS BIGINT) * 4 + 1, c_custkey * 4 + 2 FROM customer
UNION ALL SELECT CAST(s_nationkey AS BIGINT) * 4 + 1, s_suppkey * 4 + 3 FROM supplier))""",
}
ARCS = "a AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)"
DEGREES = "g AS MATERIALIZED (SELECT src AS v, count(*) AS deg FROM a GROUP BY src)"
TRIANGLES = "t AS MATERIALIZED (SELECT x.src AS a, x.dst AS b, y.dst AS c FROM e x JOIN e y ON x.dst = y.src JOIN e z ON z.src = x.src AND z.dst = y.dst)"


def on(graph: str, *more: str, select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join([EDGES[graph], *more]) + "\n" + select


def triangles(graph: str) -> str:
    return on(graph, TRIANGLES, select="SELECT count(*) AS triangles FROM t")


def stats(graph: str) -> str:
    return on(
        graph, ARCS, DEGREES, TRIANGLES,
        select=f"SELECT '{graph}' AS graph, (SELECT count(*) FROM g) AS n, (SELECT count(*) FROM e) AS m, (SELECT count(*) FROM t) AS triangles, (SELECT coalesce(max(deg), 0) FROM g) AS max_degree",
    )


def peeled(gamma: peel.Schedule, rounds: int) -> list[str]:
    """Unrolled passes: arcs a<i>, degrees d<i> (v, deg, low)."""
    out = ["a0 AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)"]
    for i in range(rounds):
        g = min(float(gamma(i)), 1e15)
        out.append(f"d{i} AS MATERIALIZED (SELECT src AS v, count(*) AS deg, count(*) <= {g!r} AS low FROM a{i} GROUP BY src)")
        out.append(f"a{i + 1} AS MATERIALIZED (SELECT a.src, a.dst FROM a{i} a JOIN d{i} x ON x.v = a.src AND NOT x.low JOIN d{i} y ON y.v = a.dst AND NOT y.low)")
    return out


def peel_trace(graph: str, gamma: peel.Schedule, rounds: int, found: bool = False) -> str:
    parts, ctes = [], peeled(gamma, rounds)
    for i in range(rounds):
        if found:
            ctes.append(
                f"h{i} AS MATERIALIZED (SELECT p.dst AS w, q.dst AS v, count(*) AS heard FROM a{i} p JOIN d{i} l ON l.v = p.src AND l.low JOIN a{i} q ON q.src = p.src AND q.dst <> p.dst GROUP BY ALL)"
            )
            ctes.append(
                f"f{i} AS (SELECT h.heard, CAST(x.low AS INTEGER) + CAST(y.low AS INTEGER) AS ends FROM h{i} h JOIN a{i} o ON o.src = h.w AND o.dst = h.v JOIN d{i} x ON x.v = h.w JOIN d{i} y ON y.v = h.v)"
            )
        more = "".join(f", (SELECT CAST(coalesce(sum(heard), 0) AS BIGINT) FROM f{i} WHERE ends = {k}) AS found{2 * k + 2}" for k in range(3)) if found else ""
        parts.append(
            f"SELECT {i} AS round, CAST({float(gamma(i))!r} AS DOUBLE) AS gamma, count(*) AS vertices, CAST(sum(deg) / 2 AS BIGINT) AS edges, CAST(sum(CAST(low AS INTEGER)) AS BIGINT) AS peeled, CAST(sum(CASE WHEN low THEN deg * deg ELSE 0 END) AS BIGINT) AS messages{more} FROM d{i} HAVING count(*) > 0"
        )
    return on(graph, *ctes, select=" UNION ALL ".join(parts))


def peel_levels(graph: str, gamma: peel.Schedule, rounds: int) -> str:
    """level, vertices with edges at removal."""
    parts = [f"SELECT {i} AS level, count(*) AS vertices, CAST(sum(deg) AS BIGINT) AS degree_sum FROM d{i} WHERE low HAVING count(*) > 0" for i in range(rounds)]
    return on(graph, *peeled(gamma, rounds), select=" UNION ALL ".join(parts))


def survivors(threshold: str, name: str = "r", start: str = "SELECT 0 AS it, src, dst FROM a", keys: tuple[str, ...] = ()) -> str:
    """Arcs left before each pass `it`; a vertex goes whose degree is at most the threshold (of it and the keys)."""
    ks = "".join(f"{k}, " for k in keys)
    return f"""{name} AS ({start} UNION ALL SELECT {ks}it + 1, src, dst FROM (SELECT *, {threshold} AS g FROM
(SELECT *, count(*) OVER (PARTITION BY {ks}src) AS ds, count(*) OVER (PARTITION BY {ks}dst) AS dd FROM {name})) WHERE ds > g AND dd > g)"""


def passes(threshold: str, name: str = "r", keys: tuple[str, ...] = ()) -> list[str]:
    """f: degrees before each pass; tr: it, vertices, edges, peeled, messages."""
    ks = "".join(f"{k}, " for k in keys)
    return [
        f"f AS MATERIALIZED (SELECT *, ds <= {threshold} AS low FROM (SELECT {ks}it, src AS v, count(*) AS ds FROM {name} GROUP BY ALL))",
        f"tr AS MATERIALIZED (SELECT {ks}it, count(*) AS vertices, CAST(sum(ds) // 2 AS BIGINT) AS edges, CAST(sum(CAST(low AS INTEGER)) AS BIGINT) AS peeled, CAST(sum(CASE WHEN low THEN ds * ds ELSE 0 END) AS BIGINT) AS messages FROM f GROUP BY ALL)",
    ]


# waves of least degree: wv holds the arcs before each wave, wk the bound of the wave, lw the wave of each vertex
WAVES = [
    """wv AS (SELECT 0 AS it, CAST(0 AS BIGINT) AS k, src, dst FROM a UNION ALL SELECT it + 1, k2, src, dst FROM (SELECT it, src, dst, ds, dd, greatest(k, min(ds) OVER ()) AS k2 FROM
(SELECT *, count(*) OVER (PARTITION BY src) AS ds, count(*) OVER (PARTITION BY dst) AS dd FROM wv)) WHERE ds > k2 AND dd > k2)""",
    "ws AS MATERIALIZED (SELECT it, src AS v, count(*) AS c, max(k) AS k FROM wv GROUP BY it, src)",
    "wk AS MATERIALIZED (SELECT it, greatest(max(k), min(c)) AS k2, min(c) AS least, count(*) AS n, CAST(sum(c) // 2 AS BIGINT) AS m FROM ws GROUP BY it)",
    "lw AS (SELECT v, it AS level FROM ws JOIN wk USING (it) WHERE c <= k2)",
    "core AS MATERIALIZED (SELECT CAST(coalesce(max(least), 0) AS BIGINT) AS core FROM wk)",
]
# waves of at most 2.5 times the mean degree
MEAN_WAVES = [
    """wv AS (SELECT 0 AS it, src, dst FROM a UNION ALL SELECT it + 1, src, dst FROM (SELECT it, src, dst, ds, dd, greatest(min(ds) OVER (), 2.5 * count(*) OVER () / round(sum(1.0 / ds) OVER ())) AS b FROM
(SELECT *, count(*) OVER (PARTITION BY src) AS ds, count(*) OVER (PARTITION BY dst) AS dd FROM wv)) WHERE ds > b AND dd > b)""",
    "ws AS MATERIALIZED (SELECT it, src AS v, count(*) AS c FROM wv GROUP BY it, src)",
    "wk AS MATERIALIZED (SELECT it, greatest(min(c), 2.5 * sum(c) / count(*)) AS k2 FROM ws GROUP BY it)",
    "lw AS (SELECT v, it AS level FROM ws JOIN wk USING (it) WHERE c <= k2)",
]
NO_WAVES = ["lw AS (SELECT CAST(NULL AS BIGINT) AS v, CAST(NULL AS BIGINT) AS level)"]
# arcs from the lower to the higher (level, degree, id)
RANKED = """rk AS MATERIALIZED (SELECT g.v, coalesce(level, 1073741824) AS l, deg FROM g LEFT JOIN lw ON lw.v = g.v),
o AS MATERIALIZED (SELECT CASE WHEN (x.l, x.deg, x.v) < (y.l, y.deg, y.v) THEN src ELSE dst END AS u, CASE WHEN (x.l, x.deg, x.v) < (y.l, y.deg, y.v) THEN dst ELSE src END AS v FROM e JOIN rk x ON x.v = src JOIN rk y ON y.v = dst)"""


def degeneracy(graph: str) -> str:
    return on(graph, ARCS, *WAVES, select="SELECT core AS degeneracy FROM core")


def outdegree(graph: str, how: str) -> str:
    waves = {"degree": NO_WAVES, "peel": MEAN_WAVES, "degeneracy": WAVES}[how]
    return on(graph, ARCS, DEGREES, *waves, RANKED, select="SELECT max(n) AS most FROM (SELECT count(*) AS n FROM o GROUP BY u)")


def stalled(graph: str) -> str:
    """What a constant threshold one under the degeneracy leaves is what the wave of that bound finds; without an edge nothing is left."""
    left = "coalesce((SELECT {} FROM wk WHERE least = core ORDER BY it LIMIT 1), 0)"
    return on(graph, ARCS, *WAVES, select=f"SELECT '{graph}' AS graph, CAST(core - 1 AS INTEGER) AS bound, core > 0 AS stalled, {left.format('n')} AS left_vertices, {left.format('m')} AS left_edges FROM core")


MODEL_ROUNDS = "CASE WHEN big <= s THEN 1 ELSE 1 + ceil(round(ln(greatest(big, 2)) / ln(greatest(s, 2.0)), 9)) + 2 * ceil(round(ln(greatest(big, 2)) / ln(greatest(s / 2, 2.0)), 9)) END"


def rounds(graph: str, bounds: tuple[int, ...]) -> str:
    """graph, bound, delta, method, iterations, model_rounds, messages."""
    g = "CASE method WHEN 'growing' THEN pow(CAST(b AS DOUBLE), pow(1.5, it)) ELSE b END"
    fixed = " UNION ".join(f"SELECT CAST({b} AS BIGINT) AS b" for b in bounds)
    return on(
        graph, ARCS, *WAVES,
        f"bs AS (SELECT b, 'growing' AS method FROM ({fixed} UNION SELECT core FROM core) UNION ALL SELECT core, 'constant' FROM core)",
        survivors(g, start="SELECT b, method, 0 AS it, src, dst FROM a, bs", keys=("b", "method")),
        *passes(g, keys=("b", "method")),
        "sp AS (SELECT d, pow(CAST((SELECT count(DISTINCT src) FROM a) AS DOUBLE), d) AS s FROM (SELECT unnest([0.3, 0.5, 0.9])::DOUBLE AS d))",
        select=f"SELECT '{graph}' AS graph, CAST(b AS INTEGER) AS bound, d AS delta, method, CAST(count(*) AS INTEGER) AS iterations, CAST(sum({MODEL_ROUNDS}) AS INTEGER) AS model_rounds, CAST(sum(messages) AS BIGINT) AS messages FROM (SELECT *, messages + 2 * edges AS big FROM tr, sp) GROUP BY ALL",
    )


def trace(graph: str, threshold: str) -> list[str]:
    return [ARCS, survivors(threshold), *passes(threshold)]


def correction(graph: str) -> str:
    """Twice the members of a triangle that leave first, by the growing threshold from 5."""
    g = "pow(5.0, pow(1.5, it))"
    return on(
        graph, *trace(graph, g), TRIANGLES,
        "lv AS (SELECT v, it FROM f WHERE low)",
        "tl AS (SELECT coalesce(x.it, 999) AS p, coalesce(y.it, 999) AS q, coalesce(z.it, 999) AS s FROM t LEFT JOIN lv x ON x.v = t.a LEFT JOIN lv y ON y.v = t.b LEFT JOIN lv z ON z.v = t.c)",
        "cr AS (SELECT CAST(coalesce(sum(2 * (CAST(p = least(p, q, s) AS INTEGER) + CAST(q = least(p, q, s) AS INTEGER) + CAST(s = least(p, q, s) AS INTEGER))), 0) AS BIGINT) AS raw, count(*) AS triangles FROM tl)",
        select=f"SELECT '{graph}' AS graph, raw, triangles, CASE WHEN triangles > 0 THEN round(raw / triangles, 6) END AS ratio FROM cr",
    )


def union(parts) -> str:
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)


def induced(graph: str, p) -> str:
    """Copies of p whose other pairs are no edges."""
    names, text = _embedded(p)
    pairs = [(x, y) for x in range(p.n) for y in range(x) if (x, y) not in p.edges and (y, x) not in p.edges]
    bare = " AND ".join(f"NOT EXISTS (SELECT 1 FROM a n WHERE n.src = {names[x]} AND n.dst = {names[y]})" for x, y in pairs)
    return on(graph, ARCS, select=f"SELECT CAST(count(*) // {p.automorphisms()} AS BIGINT) AS copies {text}" + (f" WHERE {bare}" if bare else ""))


def cliques(graph: str, k: int) -> str:
    """Cliques of one vertex more: two that share all but their last vertices, and an edge between those."""
    steps = ["q3 AS MATERIALIZED (SELECT a AS v1, b AS v2, c AS v3 FROM t)"]
    for j in range(4, k + 1):
        same = " AND ".join(f"x.v{i} = y.v{i}" for i in range(1, j - 1))
        steps.append(f"q{j} AS MATERIALIZED (SELECT x.*, y.v{j - 1} AS v{j} FROM q{j - 1} x JOIN q{j - 1} y ON {same} AND x.v{j - 1} < y.v{j - 1} JOIN e ON src = x.v{j - 1} AND dst = y.v{j - 1})")
    return on(graph, TRIANGLES, *steps, select=f"SELECT count(*) AS cliques FROM q{k}")


def _embedded(p, table: str = "a", keys: tuple[str, ...] = ()) -> tuple[dict[int, str], str]:
    """Columns of the vertices, and FROM and JOIN of labelled copies over both directions of the edges."""
    placed: dict[int, str] = {}
    todo, text, k = list(p.edges), "", 0
    same = "".join(f" AND {{n}}.{x} = j0.{x}" for x in keys)
    while todo:
        x, y = next((x, y) for x, y in todo if x in placed or y in placed or not text)
        todo.remove((x, y))
        if text and x not in placed:
            x, y = y, x
        n = f"j{k}"
        if not text:
            placed = {x: f"{n}.src", y: f"{n}.dst"}
            text = f"FROM {table} {n}"
        elif y in placed:
            text += f" JOIN {table} {n} ON {n}.src = {placed[x]} AND {n}.dst = {placed[y]}" + same.format(n=n)
        else:
            text += f" JOIN {table} {n} ON {n}.src = {placed[x]}" + "".join(f" AND {n}.dst <> {c}" for c in placed.values()) + same.format(n=n)
            placed[y] = f"{n}.dst"
        k += 1
    return placed, text


def pattern(graph: str, p) -> str:
    """Labelled joins over both directions, over the automorphisms."""
    return on(graph, ARCS, select=f"SELECT CAST(count(*) // {p.automorphisms()} AS BIGINT) AS copies {_embedded(p)[1]}")


def sampled_pattern(graph: str, p, plan, reps: int = 1) -> str:
    """rep, sampled, kept, overflowed, hits, estimate of a pattern's copies."""
    return on(
        graph, *sampled(graph, plan, reps),
        "b AS (SELECT rep, i, src, dst FROM s UNION ALL SELECT rep, i, dst, src FROM s)",
        f"ph AS (SELECT j0.rep, j0.i, count(*) AS n {_embedded(p, 'b', ('rep', 'i'))[1]} GROUP BY ALL)",
        f"pr AS (SELECT k.rep, CAST(coalesce(sum(CASE WHEN z.edges > {plan.space} THEN 1 ELSE 0 END), 0) AS BIGINT) AS o, CAST(coalesce(sum(CASE WHEN z.edges <= {plan.space} THEN ph.n ELSE 0 END), 0) AS BIGINT) AS n FROM (SELECT CAST(unnest(range({reps})) AS INTEGER) AS rep) k LEFT JOIN z ON z.rep = k.rep LEFT JOIN ph ON ph.rep = z.rep AND ph.i = z.i GROUP BY k.rep)",
        select=f"SELECT rep, CAST({plan.machines} AS BIGINT) AS sampled, {plan.machines} - o AS kept, o AS overflowed, n // {p.automorphisms()} AS hits, round(CASE WHEN o < {plan.machines} THEN n / (pow({plan.p!r}, {float(p.n)!r}) * ({plan.machines} - o)) / {p.automorphisms()} END, 6) AS estimate FROM pr",
    )


def sampled(graph: str, p, reps: int = 1, space: str | None = None) -> list[str]:
    """q (rep, i, v), s (rep, i, src, dst) and r (estimates) of a plan with k-wise hashes; space: SQL of a number."""
    space = space or str(p.space)
    if p.prime != hashing.P31:
        raise ValueError("products of this field need more than 64 bits")
    names = [f"c{j}" for j in range(p.k)]
    rows = ", ".join(f"({r}, {', '.join(map(str, hashing.coefficients(p.k, p.seed, r)))})" for r in range(reps))
    h = "c0"
    for c in names[1:]:
        h = f"(({h} * (v * {p.machines} + i) + {c}) % {p.prime})"
    return [
        f"u AS (SELECT v, i FROM (SELECT DISTINCT src AS v FROM (SELECT src FROM e UNION ALL SELECT dst FROM e)), (SELECT unnest(range({p.machines})) AS i))",
        f"cf AS (SELECT * FROM (VALUES {rows}) AS t(rep, {', '.join(names)}))",
        f"q AS MATERIALIZED (SELECT CAST(rep AS INTEGER) AS rep, i, v FROM u, cf WHERE {h} < {p.threshold})",
        "s AS MATERIALIZED (SELECT x.rep, x.i, e.src, e.dst FROM e JOIN q x ON x.v = e.src JOIN q y ON y.v = e.dst AND y.rep = x.rep AND y.i = x.i)",
        "z AS MATERIALIZED (SELECT rep, i, count(*) AS edges FROM s GROUP BY ALL)",
        "h AS MATERIALIZED (SELECT x.rep, x.i, count(*) AS hits FROM s x JOIN s y ON y.rep = x.rep AND y.i = x.i AND y.src = x.dst JOIN s w ON w.rep = x.rep AND w.i = x.i AND w.src = x.src AND w.dst = y.dst GROUP BY ALL)",
        f"""r AS (SELECT rep, {p.machines} AS sampled, {p.machines} - o AS kept, o AS overflowed, hits,
CASE WHEN o < {p.machines} THEN hits / (pow({p.p!r}, 3.0) * ({p.machines} - o)) END AS estimate FROM (
SELECT k.rep, CAST(coalesce(sum(CASE WHEN z.edges > {space} THEN 1 ELSE 0 END), 0) AS BIGINT) AS o, CAST(coalesce(sum(CASE WHEN z.edges <= {space} THEN h.hits ELSE 0 END), 0) AS BIGINT) AS hits
FROM (SELECT CAST(unnest(range({reps})) AS INTEGER) AS rep) k LEFT JOIN z ON z.rep = k.rep LEFT JOIN h ON h.rep = z.rep AND h.i = z.i GROUP BY k.rep))""",
    ]


# the space that an explicit plan takes from the graph: mean and four standard deviations of a sample's edges
def fair_space(p: float) -> list[str]:
    q, r = f"{p!r}::DOUBLE", f"{1 - p!r}::DOUBLE"
    return [
        ARCS, DEGREES,
        f"""sp AS MATERIALIZED (SELECT least(m, CAST(ceil({q} * {q} * m + 4 * sqrt(m * {p**2!r}::DOUBLE * {1 - p**2!r}::DOUBLE + w * {p**3!r}::DOUBLE * {r})) AS BIGINT)) AS space, m, n
FROM (SELECT CAST(sum(deg) // 2 AS BIGINT) AS m, count(*) AS n, CAST(sum(deg * (deg - 1)) AS DOUBLE) AS w FROM g))""",
    ]


FAIR = "(SELECT space FROM sp)"
