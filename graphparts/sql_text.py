"""The same results as SQL text for DuckDB, written apart from the engine that they check."""

from __future__ import annotations

RAW = {
    "copurchase": "SELECT DISTINCT a.l_partkey AS a, b.l_partkey AS b FROM lineitem a JOIN lineitem b USING (l_orderkey) WHERE a.l_partkey < b.l_partkey",
    "order_part": "SELECT 2 * l_orderkey AS a, 2 * l_partkey + 1 AS b FROM lineitem",
    "cust_part": "SELECT 2 * o_custkey AS a, 2 * l_partkey + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "cust_supp": "SELECT 2 * o_custkey AS a, 2 * l_suppkey + 1 AS b FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "supp_part": "SELECT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b FROM lineitem",
    "fk_tree": "SELECT 4 * o_orderkey AS a, 4 * o_custkey + 1 AS b FROM orders UNION ALL SELECT 4 * c_custkey + 1, 4 * c_nationkey::BIGINT + 2 FROM customer UNION ALL SELECT 4 * n_nationkey::BIGINT + 2, 4 * n_regionkey::BIGINT + 3 FROM nation",
    "order_chain": "SELECT o_orderkey AS a, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS b FROM orders",
    "event_chain": "SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events",
    "doc_lines": """SELECT x.doc_id AS a, y.doc_id AS b FROM
      (SELECT *, count(*) OVER (PARTITION BY line) AS c FROM (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 21)) x
      JOIN (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)) y USING (line)
      WHERE c BETWEEN 2 AND 50 AND x.doc_id < y.doc_id""",
    "page_shared": """SELECT x.page_id AS a, y.page_id AS b FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages) x
      JOIN (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages) y USING (path) WHERE x.page_id < y.page_id""",
    "page_host": "SELECT 2 * page_id AS a, 2 * min(page_id) OVER (PARTITION BY regexp_extract(url, '^[a-z]+://([^/]+)', 1)) + 1 AS b FROM pages",
    "page_path": """SELECT 2 * page_id AS a, 2 * (dense_rank() OVER (ORDER BY path) - 1) + 1 AS b FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS path FROM pages)""",
    "knn5": """SELECT a, b FROM (SELECT x.vec_id AS a, y.vec_id AS b, round(list_cosine_similarity(x.embedding::DOUBLE[], y.embedding::DOUBLE[]), 12) AS c FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id)
      QUALIFY row_number() OVER (PARTITION BY a ORDER BY c DESC, b) <= 5""",
    "supp_part_range": "SELECT 2 * l_suppkey AS a, 2 * l_partkey + 1 AS b FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' AND l_quantity >= 25",
    "conv_turns": "SELECT id AS a, lead(id) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM (SELECT conv_id, turn, conv_id * (SELECT greatest(100, max(turn) + 1) FROM conversations) + turn AS id FROM conversations)",
}

RAW["doc_lines_whole"] = f"""{RAW["doc_lines"]} UNION ALL SELECT first, doc_id FROM
      (SELECT doc_id, count(*) OVER (PARTITION BY line) AS c, min(doc_id) OVER (PARTITION BY line) AS first
       FROM (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 21)) WHERE c > 50"""


def h(x: str, seed: object = 0) -> str:
    return f"((((({x}) % 2147483647) * 48271 + {seed}) % 2147483647) * 16807 % 2147483647)"


def draw(x: str, seed: int = 0) -> str:
    return h(f"({h(x, seed)} * {h(x, seed)}) % 2147483647", seed + 1)


def graph(name: str, *more: str) -> str:
    """WITH clause: edges, arcs, vertices, and ``more`` common table expressions."""
    base = [
        f"raw AS ({RAW[name]})",
        "edges AS MATERIALIZED (SELECT least(a, b) AS src, greatest(a, b) AS dst FROM raw WHERE a <> b GROUP BY ALL)",
        "arcs AS MATERIALIZED (SELECT src AS v, dst AS u FROM edges UNION ALL SELECT dst, src FROM edges)",
        "vertices AS MATERIALIZED (SELECT v, count(*) AS deg FROM arcs GROUP BY v)",
    ]
    return "WITH RECURSIVE " + ",\n".join([*base, *more]) + "\n"


def random_parts(p: int, seed: int, name: str = "parts", column: str = "part") -> str:
    return f"{name} AS MATERIALIZED (SELECT v, ({h('v', seed)} % {p})::INT AS {column} FROM vertices)"


def block(p: int, by: str, name: str = "parts", column: str = "part") -> str:
    if by == "vertex":
        label = f"((row_number() OVER (ORDER BY v) - 1) * {p} // (SELECT count(*) FROM vertices))::INT"
    else:
        label = f"least(coalesce(sum(deg) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * {p} // (SELECT sum(deg) FROM vertices), {p - 1})::INT"
    return f"{name} AS MATERIALIZED (SELECT v, {label} AS {column} FROM vertices)"


SIZES = """ep AS MATERIALIZED (SELECT e.src, e.dst, a.part AS s, b.part AS d FROM edges e JOIN parts a ON a.v = e.src JOIN parts b ON b.v = e.dst),
ends AS (SELECT s AS part, s <> d AS cut FROM ep UNION ALL SELECT d, s <> d FROM ep)"""


def sizes(p: int) -> str:
    return (
        SIZES
        + f""",
sized AS MATERIALIZED (SELECT r.part, coalesce(vertices, 0)::BIGINT AS vertices, ((coalesce(incident, 0) - coalesce(cut, 0)) // 2)::BIGINT AS internal, coalesce(incident, 0)::BIGINT AS incident, coalesce(cut, 0)::BIGINT AS cut
  FROM (SELECT unnest(range({p}))::INT AS part) r
  LEFT JOIN (SELECT part, count(*) AS vertices FROM parts GROUP BY 1) USING (part)
  LEFT JOIN (SELECT part, count(*) AS incident, sum(cut::INT) AS cut FROM ends GROUP BY 1) USING (part))"""
    )


def quality(p: int) -> str:
    over = lambda a, b: f"CASE WHEN {b} > 0 THEN round({a} / {b}, 6) ELSE 0.0 END"
    return f"""SELECT n, m, c AS cut, mc AS max_cut, {over('c', 'm')} AS edge_cut_ratio, {over(f'mc * {p}', 'm')} AS scaled_max_cut,
  {over(f'mv * {p}', 'n')} AS vertex_imbalance, {over(f'mi * {p}', 'i')} AS internal_imbalance, {over(f'md * {p}', '(m * 2)')} AS incident_imbalance, {over(f'mc * {p}', '(c * 2)')} AS cut_balance
  FROM (SELECT sum(vertices)::BIGINT AS n, (sum(incident) // 2)::BIGINT AS m, (sum(cut) // 2)::BIGINT AS c, max(cut) AS mc, max(vertices) AS mv, max(internal) AS mi, max(incident) AS md, sum(internal)::BIGINT AS i FROM sized)"""


def grown(p: int, seed: int, levels: int, lowest: bool | str = False) -> tuple[list[str], str]:
    """CTEs of growth from p roots, level by level, and the last one's name."""
    out = [f"roots AS (SELECT v, (row_number() OVER (ORDER BY {h('v', seed)}, v) - 1)::INT AS part FROM vertices QUALIFY row_number() OVER (ORDER BY {h('v', seed)}, v) <= {p})", "near0 AS MATERIALIZED (SELECT * FROM roots)", "all0 AS MATERIALIZED (SELECT * FROM roots)"]
    for k in range(1, levels + 1):
        s = seed + k - 1
        pick = "min(part)" if lowest else f"arg_min(part, struct_pack(x := {h(h('v', s) + ' + part', s + 1)}, y := part))"
        if lowest == "majority":  # of the neighbours reached in the last level, the part that most have, the lowest of equals
            out.append(f"near{k} AS MATERIALIZED (SELECT v, arg_min(part, struct_pack(x := -c, y := part)) AS part FROM (SELECT a.v, n.part, count(*) AS c FROM near{k - 1} n JOIN arcs a ON a.u = n.v WHERE a.v NOT IN (SELECT v FROM all{k - 1}) GROUP BY ALL) GROUP BY v)")
            out.append(f"all{k} AS MATERIALIZED (SELECT * FROM all{k - 1} UNION ALL SELECT * FROM near{k})")
            continue
        out.append(f"near{k} AS MATERIALIZED (SELECT v, {pick} AS part FROM (SELECT DISTINCT a.v, n.part FROM near{k - 1} n JOIN arcs a ON a.u = n.v WHERE a.v NOT IN (SELECT v FROM all{k - 1})) GROUP BY v)")
        out.append(f"all{k} AS MATERIALIZED (SELECT * FROM all{k - 1} UNION ALL SELECT * FROM near{k})")
    out.append(f"parts AS MATERIALIZED (SELECT v, coalesce(part, ({h('v', seed + 9)} % {p})::INT) AS part FROM vertices LEFT JOIN all{levels} USING (v))")
    return out, "parts"


def majority(sweeps: int, first: str = "v") -> list[str]:
    out = [f"lab0 AS MATERIALIZED (SELECT v, {first} AS part FROM vertices)"]
    for k in range(sweeps):
        out.append(
            f"lab{k + 1} AS MATERIALIZED (SELECT v, part FROM (SELECT a.v, t.part, count(*) AS n, t.part = any_value(o.part) AS own FROM arcs a JOIN lab{k} t ON t.v = a.u JOIN lab{k} o ON o.v = a.v GROUP BY a.v, t.part)"
            " QUALIFY row_number() OVER (PARTITION BY v ORDER BY n DESC, own DESC, part) = 1)"
        )
    return out


def factors(n: int, total: int = 45, x: float = 1.0, y: float = 0.25) -> list[float]:
    """The first ``n`` values of a line from y towards x over ``total`` sweeps."""
    return [y + 0.0 if not t else (x - y) * (t / total) + y for t in range(n)]


def sweeps(kinds: list[str], p: int, n_workers: int, factors: list[float], rat: float = 0.1, quota: str = "apportion", by: str = "degree") -> list[str]:
    """CTE chain of set-mode sweeps from ``parts`` and ``owners``; the last is ``parts<k>``.

    ``bias<k>`` holds the biases: after an edge balancing sweep that began with edges over their limit the first grows, else the second.
    """
    out = ["parts0 AS MATERIALIZED (SELECT * FROM parts)", f"imb AS (SELECT (1.0::DOUBLE + {rat}::DOUBLE) * (SELECT count(*) FROM vertices) / {p} AS v, (1.0::DOUBLE + {rat}::DOUBLE) * (SELECT count(*) FROM edges) / {p} AS e)"]
    out.append("bias0 AS (SELECT 1.0::DOUBLE AS re, 1.0::DOUBLE AS rc)")
    for s, (kind, f) in enumerate(zip(kinds, factors, strict=True)):
        edge, balance = kind.startswith("edge"), kind.endswith("balance")
        f_, mult = f"{f!r}::DOUBLE", f"{n_workers * f!r}::DOUBLE"
        wt = "re * greatest(me / greatest(se, 1) - 1, 0::DOUBLE) + rc * greatest(mc::DOUBLE / greatest(sc, 1) - 1, 0::DOUBLE)" if edge else "greatest(iv / greatest(sv, 1) - 1, 0::DOUBLE)"
        score = ("h.dsum" if by == "degree" else "h.n") + " * st.wt" if balance else "h.n::DOUBLE"
        fits = "st.sv + 1 <= st.mv" + (" AND st.se + h.n <= st.me AND st.sc + d.deg - 2 * h.n <= st.mc" if edge else "")
        extra = f" AND st.se + {mult} * used_e <= st.me AND st.sc + {mult} * used_c <= st.mc::DOUBLE" if edge else ""
        ok = f"used <= st.room // {n_workers} + CASE WHEN (owner + new + {s}) % {n_workers} < st.room % {n_workers} THEN 1 ELSE 0 END" if quota == "apportion" else f"st.sv + {mult} * (used - 1) + 1 <= st.mv"
        line = "OVER (PARTITION BY owner, new ORDER BY gain DESC, v ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
        out += [
            f"hist{s} AS MATERIALIZED (SELECT a.v, q.part, count(*) AS n, sum(d.deg)::BIGINT AS dsum FROM arcs a JOIN parts{s} q ON q.v = a.u JOIN vertices d ON d.v = a.u GROUP BY a.v, q.part)",
            f"""size{s} AS MATERIALIZED (SELECT r.part, coalesce(sv, 0) AS sv, coalesce(se, 0) AS se, coalesce(sc, 0) AS sc FROM (SELECT unnest(range({p}))::INT AS part) r
              LEFT JOIN (SELECT part, count(*) AS sv FROM parts{s} GROUP BY part) USING (part)
              LEFT JOIN (SELECT q.part, (sum(CASE WHEN x.part = q.part THEN n ELSE 0 END) // 2)::BIGINT AS se, sum(CASE WHEN x.part <> q.part THEN n ELSE 0 END)::BIGINT AS sc FROM hist{s} x JOIN parts{s} q ON q.v = x.v GROUP BY q.part) USING (part))""",
            f"lim{s} AS (SELECT greatest(max(sv)::DOUBLE, any_value(imb.v)) AS mv, greatest(max(se)::DOUBLE, any_value(imb.e)) AS me, max(sc) AS mc, any_value(imb.v) AS iv FROM size{s}, imb)",
            f"state{s} AS MATERIALIZED (SELECT *, {wt} AS wt, greatest(floor((mv - sv) / {f_})::BIGINT, 0) AS room FROM size{s}, lim{s}, bias{s})",
            f"bias{s + 1} AS MATERIALIZED (SELECT CASE WHEN top > e THEN re + 1 ELSE re END AS re, CASE WHEN top > e THEN rc ELSE rc + 1 END AS rc FROM bias{s}, (SELECT max(se) AS top FROM size{s}), imb)" if edge and balance else f"bias{s + 1} AS (SELECT * FROM bias{s})",
            f"""best{s} AS MATERIALIZED (SELECT *, max(CASE WHEN own THEN score END) OVER (PARTITION BY v) AS own_score FROM (SELECT h.v, q.part AS old, h.part, o.owner, h.n, d.deg, {score} AS score, h.part = q.part AS own
              FROM hist{s} h JOIN parts{s} q ON q.v = h.v JOIN vertices d ON d.v = h.v JOIN owners o ON o.v = h.v JOIN state{s} st ON st.part = h.part WHERE ({fits}) OR h.part = q.part)
              QUALIFY row_number() OVER (PARTITION BY v ORDER BY score DESC, own DESC, part) = 1)""",
            f"""moves{s} AS MATERIALIZED (SELECT x.v, x.old, x.new, x.owner FROM (SELECT *, count(*) {line} AS used, sum(add_e) {line} AS used_e, sum(add_c) {line} AS used_c FROM
              (SELECT v, old, part AS new, score - coalesce(own_score, 0) AS gain, owner, n AS add_e, deg - 2 * n AS add_c FROM best{s} WHERE part <> old AND score > 0)) x JOIN state{s} st ON st.part = x.new WHERE {ok}{extra})""",
            f"parts{s + 1} AS MATERIALIZED (SELECT q.v, coalesce(m.new, q.part) AS part FROM parts{s} q LEFT JOIN moves{s} m ON m.v = q.v)",
        ]
    return out


def levels(sources: str, n: int, name: str = "bfs") -> list[str]:
    """BFS from ``sources`` (a query of source), up to n levels: ``bfs(source, v, dist)``."""
    f, s = f"{name}_f", f"{name}_s"
    out = [f"{f}0 AS MATERIALIZED (SELECT source, source AS v, 0 AS dist FROM ({sources}))", f"{s}0 AS MATERIALIZED (SELECT * FROM {f}0)"]
    for k in range(1, n + 1):
        out.append(f"{f}{k} AS MATERIALIZED (SELECT DISTINCT f.source, a.u AS v, {k} AS dist FROM {f}{k - 1} f JOIN arcs a ON a.v = f.v WHERE NOT EXISTS (SELECT 1 FROM {s}{k - 1} s WHERE s.source = f.source AND s.v = a.u))")
        out.append(f"{s}{k} AS MATERIALIZED (SELECT * FROM {s}{k - 1} UNION ALL SELECT * FROM {f}{k})")
    out.append(f"{name} AS MATERIALIZED (SELECT * FROM {s}{n})")
    return out


def farthest(rounds: int, n: int, seed: int = 17) -> list[str]:
    """Rounds of BFS of up to n levels, each from one of the vertices farthest from the last source: ``far0``, ``far1`` and so on."""
    out, source = [], f"SELECT v AS source FROM vertices ORDER BY {h('v', seed)}, v LIMIT 1"
    for k in range(rounds):
        out += levels(source, n, f"far{k}")
        source = f"SELECT v AS source FROM far{k} WHERE dist = (SELECT max(dist) FROM far{k}) ORDER BY {h('v', seed + k)}, v LIMIT 1"
    return out


def cores(ks: list[int], rounds: int) -> list[str]:
    out, name = [], "edges"
    alive = ["SELECT v, 0 AS core FROM vertices"]
    for k in ks:
        for r in range(rounds):
            nxt = f"core{k}_{r}"
            out.append(f"{nxt} AS MATERIALIZED (SELECT * FROM {name} WHERE src IN (SELECT v FROM (SELECT src AS v FROM {name} UNION ALL SELECT dst FROM {name}) GROUP BY v HAVING count(*) >= {k}) AND dst IN (SELECT v FROM (SELECT src AS v FROM {name} UNION ALL SELECT dst FROM {name}) GROUP BY v HAVING count(*) >= {k}))")
            name = nxt
        alive.append(f"SELECT v, {k} FROM (SELECT src AS v FROM {name} UNION SELECT dst FROM {name})")
    out.append(f"cored AS (SELECT v, max(core)::INT AS core FROM ({' UNION ALL '.join(alive)}) GROUP BY v)")
    return out


def ranks(iterations: int, damping: float = 0.85) -> list[str]:
    out = ["r0 AS MATERIALIZED (SELECT v, deg, 1.0::DOUBLE / (SELECT count(*) FROM vertices) AS rank FROM vertices)"]
    for k in range(iterations):
        out.append(f"r{k + 1} AS MATERIALIZED (SELECT r.v, r.deg, (1 - {damping}::DOUBLE) / (SELECT count(*) FROM vertices) + {damping}::DOUBLE * coalesce(g.got, 0) AS rank FROM r{k} r LEFT JOIN (SELECT a.u AS v, sum(q.rank / q.deg) AS got FROM arcs a JOIN r{k} q ON q.v = a.v GROUP BY a.u) g ON g.v = r.v)")
    return out


def canonical(draws: str) -> str:
    return f"SELECT least(a, b)::BIGINT AS src, greatest(a, b)::BIGINT AS dst FROM ({draws}) WHERE a <> b GROUP BY ALL"


#: Generators draw for each order, which is the counter; so the graph grows with the table.
_ORDERS = "(SELECT o_orderkey AS id, (SELECT count(*) // 8 FROM orders) AS eighth, (SELECT max(o_orderkey) FROM orders) AS top FROM orders)"


def erdos_renyi(seed: int = 42) -> str:
    """Of as many vertices as an eighth of the orders."""
    return canonical(f"SELECT {h('id', seed)} % eighth AS a, {draw('id', seed + 1)} % eighth AS b FROM {_ORDERS}")


def high_diameter(d: int, seed: int = 42) -> str:
    return canonical(f"SELECT * FROM (SELECT id // {d} AS a, id // {d} - {d - 1} + {draw('id', seed)} % {2 * d - 1} AS b, top // {d} AS last FROM {_ORDERS}) WHERE b >= 0 AND b <= last")


def rmat(scale: int, seed: int = 42) -> str:
    draws = [f"(x * {pow(48271, k + 1, 2147483647)} % 2147483647 * 100 / 2147483647)" for k in range(scale)]
    a = " + ".join(f"(CASE WHEN {q} < 76 THEN 0 ELSE {1 << (scale - 1 - k)} END)" for k, q in enumerate(draws))
    b = " + ".join(f"(CASE WHEN {q} < 57 OR ({q} >= 76 AND {q} < 95) THEN 0 ELSE {1 << (scale - 1 - k)} END)" for k, q in enumerate(draws))
    return canonical(f"SELECT {a} AS a, {b} AS b FROM (SELECT ({h('id', seed)} * {h('id', seed)}) % 2147483647 AS x FROM {_ORDERS})")


def mesh3d(x: int, y: int) -> str:
    """The customers as points of a grid of ``x`` by ``y`` by as many as there are."""
    one = f"SELECT id, id % {x} AS x, id // {x} % {y} AS y, id // {x * y} AS z FROM (SELECT c_custkey AS id FROM customer)"
    steps = "(SELECT i, j, k FROM (VALUES (-1), (0), (1)) a(i), (VALUES (-1), (0), (1)) b(j), (VALUES (0), (1)) c(k) WHERE k > 0 OR j > 0 OR (j = 0 AND i > 0))"
    return f"SELECT p.id AS src, q.id AS dst FROM ({one}) p, {steps} s JOIN ({one}) q ON q.x = p.x + i AND q.y = p.y + j AND q.z = p.z + k"


def planted(size: int, inside: int, across: int, seed: int = 42) -> str:
    """``size`` vertices a block; the blocks of the orders up to the last one's."""
    k, end = inside + across, draw("id", seed)
    return canonical(f"SELECT id // {k} AS a, CASE WHEN id % {k} < {inside} THEN id // {k} // {size} * {size} + {end} % {size} ELSE {end} % ((top // {k} // {size} + 1) * {size}) END AS b FROM {_ORDERS}")
