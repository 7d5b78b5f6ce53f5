"""SQL over the given tables that states each workload's result."""

from __future__ import annotations

from motifjoin.plans.query import PATTERNS, JoinQuery

#: Edge relations as SQL; every one selects distinct (src, dst).
GRAPHS: dict[str, str] = {
    "k5": "SELECT CAST(a.r_regionkey AS BIGINT) AS src, CAST(b.r_regionkey AS BIGINT) AS dst FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey",
    "basket": """SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey
        JOIN orders o ON o.o_orderkey = a.l_orderkey WHERE o.o_orderpriority LIKE '1-%' AND o.o_orderstatus = 'F'""",
    "whole_basket": """SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey
        JOIN orders o ON o.o_orderkey = a.l_orderkey""",
    "wheel": """SELECT CAST(-1 AS BIGINT) AS src, c_custkey AS dst FROM customer UNION ALL SELECT c_custkey, -1 FROM customer
        UNION ALL SELECT c_custkey, c_custkey + 1 FROM customer WHERE c_custkey + 1 <= (SELECT max(c_custkey) FROM customer)""",
    "hub": """SELECT c_custkey AS src, CAST(-1 - c_nationkey AS BIGINT) AS dst FROM customer UNION ALL SELECT CAST(-1 - c_nationkey AS BIGINT), c_custkey FROM customer""",
    "event": """SELECT DISTINCT user_id AS src, TRY_CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst FROM events
        WHERE event_type = 'purchase' AND TRY_CAST(json_extract_string(props, '$.k') AS BIGINT) <> user_id""",
    "page": """SELECT a.page_id AS src, b.page_id AS dst FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS token FROM pages) a
        JOIN (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS token FROM pages) b ON a.token = b.token AND a.page_id < b.page_id
        GROUP BY 1, 2 HAVING count(*) >= 3""",
    "label": "SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.label = b.label AND b.vec_id > a.vec_id AND b.vec_id - a.vec_id <= 40",
    "turn": "SELECT a.conv_id * (SELECT max(turn) + 1 FROM conversations) + a.turn AS src, b.conv_id * (SELECT max(turn) + 1 FROM conversations) + b.turn AS dst FROM (SELECT DISTINCT conv_id, turn FROM conversations) a JOIN (SELECT DISTINCT conv_id, turn FROM conversations) b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
}
DAILY = """SELECT CAST(ts AS DATE) AS day, user_id AS src, TRY_CAST(json_extract_string(props, '$.k') AS BIGINT) AS dst, event_type, ts, event_id FROM events
    WHERE event_type IN ('purchase', 'error') AND TRY_CAST(json_extract_string(props, '$.k') AS BIGINT) <> user_id"""


def with_graph(graph: str, body: str) -> str:
    """A query over the relation ``e``."""
    return f"WITH e AS ({GRAPHS[graph]}) {body}"


def pattern_sql(query: JoinQuery, relation: dict[str, str] | str = "e", columns: str | None = None) -> str:
    """The pattern as joins of one relation per atom (``e`` or a name per relation, columns src/dst or c0..)."""
    where, first = [], {}
    tables = []
    for i, atom in enumerate(query.atoms):
        name = relation if isinstance(relation, str) else relation[atom.relation]
        tables.append(f"{name} t{i}")
        cols = ["src", "dst"] if columns is None else [f"c{k}" for k in range(len(atom.attrs))]
        for a, c in zip(atom.attrs, cols):
            if a in first:
                where.append(f"t{i}.{c} = {first[a]}")
            else:
                first[a] = f"t{i}.{c}"
    where += [f"{first[l]} {op} {first[r]}" for l, op, r in query.filters]
    select = ", ".join(f"{first[a]} AS {a}" for a in (query.order or query.attrs))
    return f"SELECT DISTINCT {select} FROM {', '.join(tables)}" + (f" WHERE {' AND '.join(where)}" if where else "")


def count_of(sql: str) -> str:
    return f"SELECT CAST(count(*) AS BIGINT) AS n FROM ({sql}) q"


def rows_of(name: str, graph: str = "basket") -> str:
    return with_graph(graph, pattern_sql(PATTERNS[name]))


MIXED = f"""base AS ({GRAPHS["basket"]}), old_e AS (SELECT * FROM base WHERE (src + dst) % 10 <> 0), new_e AS (SELECT * FROM base WHERE (src + dst) % 10 <> 1)"""


def change_sql(name: str) -> str:
    """New result minus old result, with signs."""
    q = PATTERNS[name]
    cols = ", ".join(q.order)
    return f"WITH {MIXED}, o AS ({pattern_sql(q, 'old_e')}), n AS ({pattern_sql(q, 'new_e')}) SELECT {cols}, CAST(1 AS INTEGER) AS w FROM (SELECT * FROM n EXCEPT SELECT * FROM o) UNION ALL SELECT {cols}, CAST(-1 AS INTEGER) FROM (SELECT * FROM o EXCEPT SELECT * FROM n)"


def rule_sums_sql(name: str = "triangle") -> str:
    """Per rule, the sum of signs: changes of one atom, new before, old after."""
    q = PATTERNS[name]
    delta = "d AS (SELECT src, dst, 1 AS w FROM base WHERE (src + dst) % 10 = 0 UNION ALL SELECT src, dst, -1 FROM base WHERE (src + dst) % 10 = 1)"
    parts = []
    for i in range(len(q.atoms)):
        names, where, first = [], [], {}
        for j, atom in enumerate(q.atoms):
            names.append(f"{'d' if i == j else 'new_e' if j < i else 'old_e'} t{j}")
            for a, c in zip(atom.attrs, ("src", "dst")):
                if a in first:
                    where.append(f"t{j}.{c} = {first[a]}")
                else:
                    first[a] = f"t{j}.{c}"
        parts.append(f"SELECT CAST({i} AS INTEGER) AS rule, CAST(coalesce(sum(t{i}.w), 0) AS BIGINT) AS net FROM {', '.join(names)} WHERE {' AND '.join(where)}")
    return f"WITH {MIXED}, {delta} " + " UNION ALL ".join(parts)


PROPOSALS = """, f AS (SELECT src AS v, count(*) AS c FROM e GROUP BY 1) SELECT CAST(0 AS BIGINT) AS stage, 'a3' AS attr, CAST(count(*) AS BIGINT) AS prefixes,
    CAST(coalesce(sum(least(f1.c, f2.c)), 0) AS BIGINT) AS proposals FROM e JOIN f f1 ON f1.v = e.src JOIN f f2 ON f2.v = e.dst"""


def wedge_sql(graph: str) -> str:
    return with_graph(graph, "SELECT CAST(count(*) AS BIGINT) AS n FROM e a JOIN e b ON a.dst = b.src")


def proposals_sql(graph: str) -> str:
    return f"WITH e AS ({GRAPHS[graph]})" + PROPOSALS


#: Degree ranks: by degree, then vertex.
RANKED = """, v AS (SELECT v, count(*) AS d FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY 1), r AS (SELECT v, row_number() OVER (ORDER BY d, v) - 1 AS k FROM v)"""
SYMMETRIC = """, s AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e)"""


def agm_sql(exponents: dict[str, tuple[int, int]]) -> str:
    """The whole part of E to the power of numerator / denominator (1 or 2), by correction of a root in doubles."""
    rows = []
    for name, (num, den) in exponents.items():
        power = " * ".join(["n"] * num)
        root = "p" if den == 1 else "(SELECT max(r) FROM (SELECT unnest([CAST(floor(sqrt(CAST(p AS DOUBLE))) AS HUGEINT) + d FOR d IN [-2, -1, 0, 1, 2]]) AS r) WHERE r >= 0 AND r * r <= p)"
        rows.append(f"SELECT '{name}' AS pattern, CAST({num} AS BIGINT) AS numerator, CAST({den} AS BIGINT) AS denominator, CAST({root} AS VARCHAR) AS bound FROM (SELECT {power} AS p FROM (SELECT CAST(count(*) AS HUGEINT) AS n FROM e))")
    return with_graph("basket", " UNION ALL ".join(rows))


#: Prefixes and proposals by method: the join proposes from smallest lists, exploration takes all neighbours of any member.
INTERMEDIATES = f""", s AS (SELECT src, dst FROM e UNION SELECT dst, src FROM e), f AS (SELECT src AS v, count(*) AS c FROM e GROUP BY 1),
    t AS ({{triangle}}), q AS ({{four_clique}}),
    g3 AS (SELECT count(*) AS n FROM (SELECT e.src, e.dst, s.dst AS x FROM e JOIN s ON s.src = e.src UNION SELECT e.src, e.dst, s.dst FROM e JOIN s ON s.src = e.dst)),
    g4 AS (SELECT count(*) AS n FROM (SELECT t.*, s.dst AS x FROM t JOIN s ON s.src = a1 UNION SELECT t.*, s.dst FROM t JOIN s ON s.src = a2 UNION SELECT t.*, s.dst FROM t JOIN s ON s.src = a3)),
    p3 AS (SELECT coalesce(sum(least(f1.c, f2.c)), 0) AS n FROM e JOIN f f1 ON f1.v = e.src JOIN f f2 ON f2.v = e.dst),
    p4 AS (SELECT coalesce(sum(least(f1.c, f2.c, f3.c)), 0) AS n FROM t JOIN f f1 ON f1.v = a1 JOIN f f2 ON f2.v = a2 JOIN f f3 ON f3.v = a3),
    x3 AS (SELECT (SELECT count(*) FROM s) + (SELECT count(*) FROM e) + (SELECT n FROM g3) + (SELECT count(*) FROM t) AS n)
    SELECT 'triangle' AS pattern, 'static' AS method, CAST(n AS BIGINT) AS n FROM p3
    UNION ALL SELECT 'triangle', 'exploration', CAST(n AS BIGINT) FROM x3
    UNION ALL SELECT 'triangle', 'binary', CAST(count(*) AS BIGINT) FROM e a JOIN e b ON a.dst = b.src
    UNION ALL SELECT 'four_clique', 'static', CAST(p3.n + p4.n AS BIGINT) FROM p3, p4
    UNION ALL SELECT 'four_clique', 'exploration', CAST(x3.n + g4.n + (SELECT count(*) FROM q) AS BIGINT) FROM x3, g4"""


def intermediates_sql() -> str:
    return f"WITH e AS ({GRAPHS['basket']})" + INTERMEDIATES.format(triangle=pattern_sql(PATTERNS["triangle"]), four_clique=pattern_sql(PATTERNS["four_clique"]))


def triangle_costs_sql(workers: int) -> str:
    """Tuples that workers receive when lists are looked up by their key's value: a round per lookup."""
    w = workers
    lists = {
        "p1": f"SELECT src % {w} AS k FROM e",
        "p2": f"SELECT e.dst % {w} AS k FROM e WHERE src IN (SELECT v FROM f)",
        "c1": f"SELECT (a1 * 31 + a3) % {w} AS k FROM c",
        "c2": f"SELECT (a2 * 31 + a3) % {w} AS k FROM c",
    }
    rounds = " UNION ALL ".join(f"SELECT '{n}' AS r, k, count(*) AS n FROM ({q}) GROUP BY 2" for n, q in lists.items())
    body = f""", f AS (SELECT src AS v, count(*) AS c FROM e GROUP BY 1),
        x AS (SELECT e.src AS a1, e.dst AS a2, CASE WHEN f1.c <= f2.c THEN e.src ELSE e.dst END AS v FROM e JOIN f f1 ON f1.v = e.src JOIN f f2 ON f2.v = e.dst),
        c AS (SELECT a1, a2, e.dst AS a3 FROM x JOIN e ON e.src = x.v), l AS ({rounds})
        SELECT CAST(4 AS BIGINT) AS rounds, CAST((SELECT max(n) FROM l) AS BIGINT) AS load, CAST((SELECT sum(n) FROM l) AS BIGINT) AS communication,
        CAST((SELECT count(*) FROM e) + (SELECT max(n) FROM (SELECT sum(n) AS n FROM l GROUP BY r)) AS BIGINT) AS memory,
        CAST((SELECT count(*) FROM e) + (SELECT count(*) FROM c) AS BIGINT) AS intermediates, CAST((SELECT count(*) FROM c) AS BIGINT) AS proposals"""
    return f"WITH e AS ({GRAPHS['basket']})" + body


def lives_sql(name: str, lives: str) -> str:
    """``t(since, until)``: how long each match of a pattern lives, from ``lives(src, dst, since, until)``."""
    q = PATTERNS[name]
    where, first, tables = [], {}, []
    for i, atom in enumerate(q.atoms):
        tables.append(f"{lives} t{i}")
        for a, c in zip(atom.attrs, ("src", "dst")):
            where.append(f"t{i}.{c} = {first[a]}") if a in first else first.setdefault(a, f"t{i}.{c}")
    n = range(len(q.atoms))
    return f"SELECT greatest({', '.join(f't{i}.since' for i in n)}) AS since, least({', '.join(f't{i}.until' for i in n)}) AS until FROM {', '.join(tables)} WHERE {' AND '.join(where)}"


def batches_sql(n: int, edges: str = "e") -> str:
    """Lifetimes in versions under ``batch_sequence``: half preloaded, the rest inserted and a third of the first half deleted."""
    g = f"((src * 31 + dst * 17) % {2 * n})"
    return f"SELECT src, dst, CASE WHEN {g} < {n} THEN {g} + 1 ELSE 0 END AS since, CASE WHEN {g} >= {n} AND (src + dst) % 3 = 0 THEN {g} - {n} + 1 END AS until FROM {edges}"


def version_changes_sql(name: str, n: int) -> str:
    """Per version the matches that came and went."""
    return with_graph("basket", f", l AS ({batches_sql(n)}), t AS ({lives_sql(name, 'l')}), c AS (SELECT since AS ver, 1 AS w FROM t WHERE since > 0 AND (until IS NULL OR since < until) UNION ALL SELECT until, -1 FROM t WHERE since < until) SELECT CAST(ver AS BIGINT) AS ver, CAST(count(*) FILTER (w > 0) AS BIGINT) AS came, CAST(count(*) FILTER (w < 0) AS BIGINT) AS went FROM c GROUP BY 1").replace(") , l", "), l")
