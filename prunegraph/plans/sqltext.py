"""Builds DuckDB SQL of the same computations in long form, from the same rules."""

from __future__ import annotations

GRAPHS = {
    "purchase": """b AS (SELECT DISTINCT o_custkey*4 AS a, l_partkey*4+1 AS p FROM orders JOIN lineitem ON l_orderkey = o_orderkey),
e AS (SELECT a AS dst, p AS src FROM b UNION ALL SELECT p AS dst, a AS src FROM b)""",
    "copurchase": """b AS (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem),
e AS (SELECT DISTINCT x.l_partkey*4+1 AS dst, y.l_partkey*4+1 AS src FROM b x JOIN b y ON x.l_orderkey = y.l_orderkey AND x.l_partkey <> y.l_partkey)""",
    "chain": """b AS (SELECT o_custkey*4 AS a, o_orderkey*4+2 AS p FROM orders UNION SELECT l_orderkey*4+2 AS a, l_partkey*4+1 AS p FROM lineitem),
e AS (SELECT a AS dst, p AS src FROM b UNION ALL SELECT p AS dst, a AS src FROM b)""",
    "supply": """b AS (SELECT DISTINCT l_suppkey*4+3 AS a, l_partkey*4+1 AS p FROM lineitem),
e AS (SELECT a AS dst, p AS src FROM b UNION ALL SELECT p AS dst, a AS src FROM b)""",
    "event": """e AS (SELECT n.event_id AS dst, o.event_id AS src FROM events n JOIN events o ON n.user_id = o.user_id AND o.ts < n.ts AND o.ts >= n.ts - INTERVAL '1' DAY)""",
    "reply": """e AS (SELECT m.conv_id*64+m.turn AS dst, q.conv_id*64+q.turn AS src FROM conversations m JOIN conversations q ON m.conv_id = q.conv_id AND abs(m.turn - q.turn) = 1)""",
    "doc": """t AS (SELECT DISTINCT doc_id, unnest(string_split_regex(lower(text), '[^a-z]+')) AS token FROM documents),
f AS (SELECT token FROM t WHERE length(token) > 2 GROUP BY token HAVING count(*) BETWEEN 2 AND 12),
k AS (SELECT t.* FROM t JOIN f USING (token)),
e AS (SELECT x.doc_id AS dst, y.doc_id AS src FROM k x JOIN k y ON x.token = y.token AND x.doc_id <> y.doc_id GROUP BY 1, 2 HAVING count(*) >= 2)""",
    "knn": """v AS (SELECT vec_id, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) AS j FROM embeddings),
d AS (SELECT p.vec_id AS dst, q.vec_id AS src, floor(sum(p.x * q.x) * 1000000 + 0.4999)::BIGINT AS dot FROM v p JOIN v q ON p.j = q.j AND p.vec_id <> q.vec_id GROUP BY 1, 2),
e AS (SELECT dst, src FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY dot DESC, src) r FROM d) WHERE r <= 8)""",
}
NODES = "nodes AS (SELECT c_custkey*4 AS node_id FROM customer UNION ALL SELECT p_partkey*4+1 FROM part)"
SPLIT = "((({n} % 65536) * 40503) % 65536) % 100"


def fixed(x: str) -> str:
    """A double as an integer of millionths, away from ties."""
    return f"CAST(floor(({x}) * 1000000 + 0.4999) AS BIGINT)"


class Plan:
    """A chain of common table expressions."""

    def __init__(self, graph: str = "purchase", nodes: str = NODES):
        self.parts = [GRAPHS[graph], nodes]
        self.n = 0

    def add(self, body: str, name: str | None = None) -> str:
        self.n += 1
        name = name or f"s{self.n}"
        self.parts.append(f"{name} AS ({body})")
        return name

    def features(self, width: int = 8) -> str:
        return self.add(f"SELECT node_id, CAST(j AS INTEGER) AS j, CAST((node_id*(j+3)+j*j) % 7 - 3 AS DOUBLE) AS x FROM nodes, range({width}) r(j)")

    def step(self, h: str, edges: str = "e", weighted: str | None = None) -> str:
        value = f"sum({weighted} * h.x)" if weighted else "avg(h.x)"
        got = self.add(f"SELECT {edges}.dst AS node_id, h.j, {value} AS x FROM {edges} JOIN {h} h ON h.node_id = {edges}.src GROUP BY 1, 2")
        return self.add(f"SELECT n.node_id, n.j, coalesce(g.x, 0) AS x FROM {h} n LEFT JOIN {got} g ON g.node_id = n.node_id AND g.j = n.j")

    def weights(self, layer: int, k: int, f_in: int, f_out: int) -> str:
        return self.add(f"SELECT CAST(j AS INTEGER) AS j, CAST(o AS INTEGER) AS o, ((7*j + 3*o + 11*{k} + 5*{layer}) % 9 - 4) / 8.0 AS w FROM range({f_in}) a(j), range({f_out}) b(o)")

    def product(self, h: str, w: str) -> str:
        return self.add(f"SELECT h.node_id, w.o AS j, sum(h.x * CAST(w.w AS DOUBLE)) AS x FROM {h} h JOIN {w} w ON w.j = h.j GROUP BY 1, 2")

    def concat(self, parts: list[tuple[str, int]]) -> str:
        first, rows = 0, []
        for name, width in parts:
            rows.append(f"SELECT node_id, j + {first} AS j, x FROM {name}")
            first += width
        return self.add(" UNION ALL ".join(rows))

    def relu(self, h: str) -> str:
        return self.add(f"SELECT node_id, j, greatest(x, 0) AS x FROM {h}")

    def layer(self, h: str, index: int, orders: range, f_in: int, f_out: int, combine: str = "concat", act: bool = True) -> str:
        parts, now, at = [], h, 0
        for k in orders:
            while at < k:
                now, at = self.step(now), at + 1
            parts.append((self.product(now, self.weights(index, k, f_in, f_out)), f_out))
        if combine == "concat":
            out = self.concat(parts)
        else:
            union = " UNION ALL ".join(f"SELECT * FROM {p}" for p, _ in parts)
            out = self.add(f"SELECT node_id, j, sum(x) / {len(parts)} AS x FROM ({union}) GROUP BY 1, 2")
        return self.relu(out) if act else out

    def select(self, body: str) -> str:
        return "WITH " + ",\n".join(self.parts) + "\n" + body

    def cells(self, h: str) -> str:
        return self.select(f"SELECT node_id, CAST(j AS INTEGER) AS ch, {fixed('x')} AS v FROM {h}")
