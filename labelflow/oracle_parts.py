"""SQL of the graph and of unrolled iterations, from which the oracles are put together."""

from __future__ import annotations

from labelflow.functions.fixed import HALF, SCALE, units

EDGES = "edges AS MATERIALIZED (SELECT l_orderkey * 2 AS u, l_partkey * 2 + 1 AS v, CAST(sum(l_quantity) AS BIGINT) AS w FROM lineitem GROUP BY 1, 2 HAVING sum(l_quantity) > 0)"
NODES = """nodes AS MATERIALIZED (SELECT o_orderkey * 2 AS node_id, CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 END AS truth FROM orders
  UNION ALL SELECT DISTINCT l_partkey * 2 + 1, CAST(NULL AS INT) FROM lineitem)"""


def arcs(edges: str = "edges", name: str = "arcs") -> str:
    return f"{name} AS MATERIALIZED (SELECT u AS src, v AS dst, w FROM {edges} UNION ALL SELECT v, u, w FROM {edges})"


def contraction(arcs: str = "arcs", nodes: str = "nodes", name: str = "cw") -> str:
    return f"""{name} AS MATERIALIZED (SELECT src AS node_id, CAST(sum(CASE WHEN truth = 0 THEN w ELSE 0 END) AS BIGINT) AS w0, CAST(sum(CASE WHEN truth = 1 THEN w ELSE 0 END) AS BIGINT) AS w1,
  CAST(sum(w) AS BIGINT) AS w_all FROM {arcs} LEFT JOIN {nodes} ON dst = node_id GROUP BY src)"""


def start(name: str = "s0", nodes: str = "nodes", cw: str = "cw", f: str = str(HALF), extra: str = "") -> str:
    return f"""{name} AS MATERIALIZED (SELECT n.node_id, CAST({f} AS BIGINT) AS f, coalesce(w0, 0) AS w0, coalesce(w1, 0) AS w1, coalesce(w_all, 0) AS w_all
  FROM {nodes} n LEFT JOIN {cw} c ON c.node_id = n.node_id {extra} WHERE n.truth IS NULL)"""


def free_arcs(s: str = "s0", arcs: str = "arcs", name: str = "fa") -> str:
    return f"{name} AS MATERIALIZED (SELECT src, dst, w FROM {arcs} WHERE src IN (SELECT node_id FROM {s}) AND dst IN (SELECT node_id FROM {s}))"


def _new(weight: str = "w") -> str:
    return f"(2 * (coalesce(m.num, 0) + s.w1 * {SCALE}) + s.w_all) // (2 * s.w_all)"


def sweeps(k: int, s: str = "s", fa: str = "fa") -> str:
    """s1 ... sk from s0."""
    return ",\n".join(
        f"""{s}{i + 1} AS MATERIALIZED (SELECT s.node_id, CAST(CASE WHEN s.w_all > 0 THEN {_new()} ELSE s.f END AS BIGINT) AS f, s.w0, s.w1, s.w_all FROM {s}{i} s
  LEFT JOIN (SELECT src, sum(w * f) AS num FROM {fa} JOIN {s}{i} t ON t.node_id = dst GROUP BY src) m ON m.src = s.node_id)"""
        for i in range(k)
    )


def frontier(k: int, delta: float, s: str = "t", fa: str = "fa", commit_small: bool = False) -> str:
    """t1 ... tk and the frontiers h1 ... hk from t0 and h0(node_id)."""
    out = []
    take = "new IS NOT NULL" if commit_small else "moved"
    for i in range(k):
        out.append(
            f"""{s}{i + 1} AS MATERIALIZED (SELECT node_id, CAST(CASE WHEN {take} THEN new ELSE f END AS BIGINT) AS f, w0, w1, w_all, moved FROM (
  SELECT *, coalesce(abs(new - f) > {units(delta)}, false) AS moved FROM (SELECT s.node_id, s.f, s.w0, s.w1, s.w_all, CASE WHEN h.node_id IS NOT NULL AND s.w_all > 0 THEN {_new()} END AS new
  FROM {s}{i} s LEFT JOIN h{i} h ON h.node_id = s.node_id LEFT JOIN (SELECT src, sum(w * f) AS num FROM {fa} JOIN {s}{i} t ON t.node_id = dst GROUP BY src) m ON m.src = s.node_id)))"""
        )
        out.append(f"h{i + 1} AS MATERIALIZED (SELECT node_id FROM {s}{i + 1} WHERE moved UNION SELECT dst FROM {fa} JOIN {s}{i + 1} ON node_id = src WHERE moved)")
    return ",\n".join(out)


def two_phase(k: int, delta: float, fa: str = "fa") -> str:
    """As `frontier`, but even ids move first (a step's table `e`) and odd ids see the result."""
    out = []
    for i in range(k):
        for s, t, parity in ((f"t{i}", f"e{i + 1}", 0), (f"e{i + 1}", f"t{i + 1}", 1)):
            was = "false" if parity == 0 else "was"
            out.append(
                f"""{t} AS MATERIALIZED (SELECT node_id, CAST(CASE WHEN big THEN new ELSE f END AS BIGINT) AS f, w0, w1, w_all, big OR {was} AS {"was" if parity == 0 else "moved"} FROM (
  SELECT *, coalesce(abs(new - f) > {units(delta)}, false) AS big FROM (SELECT s.*, CASE WHEN h.node_id IS NOT NULL AND s.node_id % 2 = {parity} AND s.w_all > 0 THEN {_new()} END AS new
  FROM {s} s LEFT JOIN h{i} h ON h.node_id = s.node_id LEFT JOIN (SELECT src, sum(w * f) AS num FROM {fa} JOIN {s} t ON t.node_id = dst GROUP BY src) m ON m.src = s.node_id)))"""
            )
        out.append(f"h{i + 1} AS MATERIALIZED (SELECT node_id FROM t{i + 1} WHERE moved UNION SELECT dst FROM {fa} JOIN t{i + 1} ON node_id = src WHERE moved)")
    return ",\n".join(out)


def components(nodes: str, arcs: str, name: str = "cc") -> str:
    """Smallest reachable id by a keyed recursive table."""
    return f"""{name}(node_id, comp_id) USING KEY (node_id) AS (SELECT node_id, node_id FROM {nodes}
  UNION SELECT a.dst, min(x.comp_id) FROM {name} x JOIN {arcs} a ON a.src = x.node_id JOIN recurring.{name} r ON r.node_id = a.dst WHERE x.comp_id < r.comp_id GROUP BY a.dst)"""


#: The batch of the update queries: orders of the last two months, and every tenth part, arrive; some older orders leave.
NEW_IDS = "SELECT o_orderkey * 2 AS node_id FROM orders WHERE o_orderdate >= (SELECT date_trunc('month', max(o_orderdate)) - INTERVAL 1 MONTH FROM orders) UNION SELECT DISTINCT l_partkey * 2 + 1 FROM lineitem WHERE l_partkey % 10 = 0"
DEL_IDS = "SELECT o_orderkey * 2 AS node_id FROM orders WHERE o_orderkey % 97 = 5 AND o_orderdate < (SELECT date_trunc('month', max(o_orderdate)) - INTERVAL 1 MONTH FROM orders)"


def update_sql(inserts: bool, deletes: bool, steps: int, delta: float, select: str, commit_small: bool = False, gates: bool = False, schedule: str = "sync") -> str:
    """The whole update: five sweeps on the old graph, the batch, component labels, and frontier steps."""
    ran = two_phase(steps, delta) if schedule == "two_phase" else frontier(steps, delta, commit_small=commit_small)
    gate = "SELECT all_arcs.* FROM all_arcs, tau WHERE w > tau OR src NOT IN (SELECT node_id FROM fresh) AND dst NOT IN (SELECT node_id FROM fresh)" if gates else "SELECT * FROM all_arcs"
    old = "old_nodes AS MATERIALIZED (SELECT * FROM nodes" + (" WHERE node_id NOT IN (SELECT node_id FROM fresh))" if inserts else ")")
    gone = f"gone AS MATERIALIZED ({DEL_IDS})" if deletes else "gone AS (SELECT CAST(0 AS BIGINT) AS node_id WHERE false)"
    fresh = f"fresh AS MATERIALIZED ({NEW_IDS})" if inserts else "fresh AS (SELECT CAST(0 AS BIGINT) AS node_id WHERE false)"
    return f"""WITH RECURSIVE {EDGES}, {NODES}, {fresh}, {gone}, {arcs()}, {old},
old_arcs AS MATERIALIZED (SELECT * FROM arcs WHERE src IN (SELECT node_id FROM old_nodes) AND dst IN (SELECT node_id FROM old_nodes)),
{contraction('old_arcs', 'old_nodes', 'cw0')}, {start('s0', 'old_nodes', 'cw0')}, {free_arcs('s0', 'old_arcs', 'fa0')}, {sweeps(5, 's', 'fa0')},
now AS MATERIALIZED (SELECT * FROM nodes WHERE node_id NOT IN (SELECT node_id FROM gone)),
all_arcs AS MATERIALIZED (SELECT * FROM arcs WHERE src NOT IN (SELECT node_id FROM gone) AND dst NOT IN (SELECT node_id FROM gone)),
tau AS MATERIALIZED (SELECT avg(w) AS tau FROM (SELECT w FROM edges WHERE u IN (SELECT node_id FROM fresh) OR v IN (SELECT node_id FROM fresh)
  UNION ALL SELECT w FROM all_arcs WHERE src < dst AND src NOT IN (SELECT node_id FROM fresh) AND dst NOT IN (SELECT node_id FROM fresh))),
now_arcs AS MATERIALIZED ({gate}),
sub AS MATERIALIZED (SELECT src, dst, w FROM now_arcs, tau WHERE w > tau AND src IN (SELECT node_id FROM fresh) AND dst IN (SELECT node_id FROM fresh)),
{components('fresh', 'sub')},
{contraction('now_arcs', 'now')},
comp AS MATERIALIZED (SELECT comp_id, coalesce(sum(w0), 0) AS w0, coalesce(sum(w1), 0) AS w1 FROM cc JOIN now USING (node_id) LEFT JOIN cw USING (node_id) WHERE truth IS NULL GROUP BY comp_id),
init AS MATERIALIZED (SELECT node_id, comp_id, CAST(CASE WHEN w0 + w1 > 0 THEN (2 * w1 * {SCALE} + w0 + w1) // (2 * (w0 + w1)) ELSE {HALF} END AS BIGINT) AS f0 FROM cc JOIN comp USING (comp_id)),
f0 AS MATERIALIZED (SELECT node_id, f0 FROM init UNION ALL SELECT node_id, f FROM s5 WHERE node_id NOT IN (SELECT node_id FROM fresh)),
{start('t0', 'now', 'cw', f'coalesce(f0.f0, {HALF})', 'LEFT JOIN f0 ON f0.node_id = n.node_id')}, {free_arcs('t0', 'now_arcs', 'fa')},
touched AS MATERIALIZED (SELECT node_id FROM fresh UNION SELECT dst FROM now_arcs JOIN fresh ON src = node_id UNION SELECT dst FROM old_arcs JOIN gone ON src = node_id),
h0 AS MATERIALIZED (SELECT node_id FROM touched WHERE node_id IN (SELECT node_id FROM t0 WHERE w_all > 0)),
{ran}
{select}"""
