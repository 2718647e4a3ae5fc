"""The sorting queries as SQL for DuckDB: ranks by a window, and each random stage replayed from its hash."""

from __future__ import annotations

from finegrain.functions.pivots import weight_table
from finegrain.operators.treemerge import depth


def digest(seed: int, level: int, purpose: str, *ids: str) -> str:
    """The portable hash of literal parts and SQL expressions."""
    tail = "||'|'||".join(f"({x})::VARCHAR" for x in ids)
    return f"('0x'||substr(md5('{seed}|{level}|{purpose}|'||{tail}),1,8))::BIGINT"


def rank_sql(table: str, columns: str, order: str) -> str:
    return f"SELECT {columns}, row_number() OVER (ORDER BY {order}) - 1 AS rank FROM {table}"


def level_ctes(source: str, nodes: int, radices: list[int], fan_in: int, seed: int = 7) -> str:
    """CTEs ``placed``, and for each level ``pick``, ``tree`` and ``routed``, over a source with ``id`` and ``c``.

    Valid while every node has at least 2b keys.
    """
    parts = [f"src AS ({source})", f"placed AS (SELECT id, c, ((row_number() OVER (ORDER BY {digest(seed, 0, 'init', 'id')}, id::VARCHAR) - 1) % {nodes})::INT AS node FROM src)"]
    rows, width = "placed", nodes
    for level, b in enumerate(radices):
        share, x = width // b, f"l{level}"
        parts.append(f"{x}_sample AS (SELECT node // {width} AS grp, node, c, id FROM {rows} QUALIFY row_number() OVER (PARTITION BY node ORDER BY {digest(seed, level, 'pick', 'id')}, id::VARCHAR) <= {2 * b})")
        parts.append(f"{x}_order AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY c, id) AS r FROM {x}_sample)")
        shift = f"CASE WHEN {digest(seed, level, 'set', 'node')} / 4294967296.0 < 0.5 THEN 0 ELSE 1 END"
        parts.append(f"{x}_pick AS (SELECT grp, node, ((r - s) // 2 - 1)::INT AS j, c, id FROM (SELECT *, {shift} AS s FROM {x}_order) WHERE (r - s) % 2 = 0 AND r - s BETWEEN 2 AND {2 * b - 2})")
        parts.append(f"{x}_t0 AS (SELECT grp, j, dense_rank() OVER (PARTITION BY grp ORDER BY node) - 1 AS idx, c, id FROM {x}_pick)")
        rounds = max(1, depth(width, fan_in))
        for t in range(1, rounds + 1):
            over = f"PARTITION BY grp, j, idx // {fan_in}"
            parts.append(
                f"{x}_t{t} AS (SELECT grp, j, idx // {fan_in} AS idx, c, id FROM {x}_t{t - 1} QUALIFY row_number() OVER ({over} ORDER BY c, id) = "
                f"CASE WHEN (idx // {fan_in} + {t}) % 2 = 1 THEN count(*) OVER ({over}) // 2 + 1 ELSE (count(*) OVER ({over}) - 1) // 2 + 1 END)"
            )
        parts.append(f"{x}_tree AS (SELECT grp, row_number() OVER (PARTITION BY grp ORDER BY c, id) - 1 AS j, c, id FROM {x}_t{rounds})")
        parts.append(
            f"{x}_bucket AS (SELECT r.id, r.c, r.node // {width} AS grp, count(p.c)::INT AS bucket FROM {rows} r LEFT JOIN {x}_tree p ON p.grp = r.node // {width} AND (p.c < r.c OR (p.c = r.c AND p.id <= r.id)) GROUP BY ALL)"
        )
        parts.append(f"{x}_routed AS (SELECT id, c, bucket, (grp * {width} + bucket * {share} + {digest(seed, level, 'route', 'id')} % {share})::INT AS node FROM {x}_bucket)")
        rows, width = f"{x}_routed", share
    return "WITH " + ",\n".join(parts)


def _events_nodes(size: int) -> str:
    return f"n AS (SELECT event_id // {size} AS node, event_id, value, row_number() OVER (PARTITION BY event_id // {size} ORDER BY {digest(7, 0, 'pick', 'event_id')}, event_id::VARCHAR) AS h FROM events WHERE event_id < {size * 100})"


def _leave_one_out(b: int, shares: tuple[float, float, float], source: str) -> str:
    """From ``source(node, value, event_id)`` with b rows a node the b - 1 pivots."""
    low = shares[0] + shares[1]
    return f"""o AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY value, event_id) AS r, {digest(7, 0, 'case', 'node')} / 4294967296.0 AS u, {digest(7, 0, 'drop', 'node')} % {b} AS d FROM {source}),
        k AS (SELECT * FROM o WHERE CASE WHEN u < {shares[0]} THEN r - 1 <> d WHEN u < {low} THEN r < {b} ELSE r > 1 END)
        SELECT node::INT AS node, (row_number() OVER (PARTITION BY node ORDER BY r) - 1)::INT AS j, value, event_id FROM k"""


def _double(b: int, size: int) -> str:
    return f"""WITH {_events_nodes(size)}, s AS (SELECT * FROM n WHERE h <= {2 * b}),
        o AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY value, event_id) AS r, CASE WHEN {digest(7, 0, 'set', 'node')} / 4294967296.0 < 0.5 THEN 0 ELSE 1 END AS s FROM s)
        SELECT node::INT AS node, ((r - s) // 2 - 1)::INT AS j, value, event_id FROM o WHERE (r - s) % 2 = 0 AND r - s BETWEEN 2 AND {2 * b - 2}"""


def _policy_ctes() -> str:
    """Pivots of all events by policy, from a tenth as many nodes of ten keys: CTE ``piv(policy, j, value, event_id)``.

    Six rounds of medians are enough for a million nodes; a round over one row changes nothing.
    """
    parts = [
        "c AS (SELECT greatest(1, count(*) // 10) AS nodes FROM events)",
        f"p AS (SELECT event_id, value, (row_number() OVER (ORDER BY {digest(7, 0, 'init', 'event_id')}, event_id::VARCHAR) - 1) % (SELECT nodes FROM c) AS node FROM events)",
        "o AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY value, event_id) AS r FROM p)",
        f"u AS (SELECT *, {digest(7, 0, 'case', 'node')} / 4294967296.0 AS u, {digest(7, 0, 'drop', 'node')} % 10 AS d FROM o)",
    ]
    chosen = []
    for name, shares in (("naive", NAIVE), ("shifted", SHIFTED), ("mixed", MIXED)):
        keep = f"CASE WHEN u < {shares[0]} THEN r - 1 <> d WHEN u < {shares[0] + shares[1]} THEN r < 10 ELSE r > 1 END"
        chosen.append(f"SELECT '{name}' AS policy, node, row_number() OVER (PARTITION BY node ORDER BY r) - 1 AS j, value, event_id FROM u WHERE {keep}")
    for name, policy in (("calibrated", "calibrated"), ("two_point", ("mix", (0.8, 0.2)))):
        rows = ", ".join(f"({j}, {i}, {w!r}::DOUBLE)" for j, ((i, w), _) in enumerate(weight_table(10, policy)[0], 1))
        picked = f"SELECT x.node, w.j, w.i + CASE WHEN {digest(7, 0, 'mix', 'x.node', 'w.j')} / 4294967296.0 < w.w THEN 0 ELSE 1 END AS r FROM (SELECT DISTINCT node FROM o) x, (VALUES {rows}) w(j, i, w)"
        chosen.append(f"SELECT '{name}' AS policy, o.node, row_number() OVER (PARTITION BY o.node ORDER BY o.r) - 1 AS j, o.value, o.event_id FROM ({picked}) q JOIN o ON o.node = q.node AND o.r = q.r")
    parts.append(f"t0 AS (SELECT policy, j, node AS idx, value, event_id FROM ({' UNION ALL '.join(chosen)}))")
    for t in range(1, 7):
        over = "PARTITION BY policy, j, idx // 10"
        parts.append(
            f"t{t} AS (SELECT policy, j, idx // 10 AS idx, value, event_id FROM t{t - 1} QUALIFY row_number() OVER ({over} ORDER BY value, event_id) = "
            f"CASE WHEN (idx // 10 + {t}) % 2 = 1 THEN count(*) OVER ({over}) // 2 + 1 ELSE (count(*) OVER ({over}) - 1) // 2 + 1 END)"
        )
    parts.append("piv AS (SELECT policy, (row_number() OVER (PARTITION BY policy ORDER BY value, event_id) - 1)::INT AS j, value, event_id FROM t6)")
    return "WITH " + ",\n".join(parts)


MIXED, NAIVE, SHIFTED = (0.25, 0.375, 0.375), (1.0, 0.0, 0.0), (0.0, 0.5, 0.5)


def oracle_sql() -> dict[str, str]:
    orders = rank_sql("orders", "o_totalprice, o_orderkey", "o_totalprice, o_orderkey")
    line = "l_orderkey, l_partkey, l_suppkey, l_linenumber"
    src = "SELECT o_orderkey AS id, o_totalprice AS c FROM orders"
    two = level_ctes(src, 64, [8, 8], 16)
    out = {name: orders for name in ("rbs_rank_orders", "rbs_naive", "rbs_shifted", "rbs_full_quantile", "rbs_calibrated", "rbs_exact_median", "rbs_truncated_tree", "rbs_lower_median_rule", "rbs_mixed_radix", "rbs_adaptive_stop", "rbs_hash_placement", "rbs_physical", "rbs_fused", "builtin_sort_orders")}
    out |= {
        "rbs_rank_lineitem_price": rank_sql("lineitem", f"l_extendedprice, {line}", f"l_extendedprice, {line}"),
        "rbs_rank_lineitem_quantity_ties": rank_sql("lineitem", f"l_quantity, l_extendedprice, {line}", f"l_quantity, l_extendedprice, {line}"),
        "rbs_rank_events_value_desc": rank_sql("events", "value, event_id", "value DESC, event_id"),
        "rbs_rank_events_ts": rank_sql("events", "event_id", "ts, event_id"),
        "rbs_rank_documents_nchars": rank_sql("documents", "n_chars, doc_id", "n_chars, doc_id"),
        "rbs_rank_customer_multi_key": rank_sql("customer", "c_mktsegment, c_acctbal, c_custkey", "c_mktsegment, c_acctbal DESC, c_custkey"),
        "rbs_rank_part_name_desc": rank_sql("part", "p_name, p_partkey", "p_name DESC, p_partkey"),
        "rbs_rank_pages_url": rank_sql("pages", "url, page_id", "url, page_id"),
        "rbs_rank_conversations": rank_sql("conversations", "conv_id, turn", "conv_id, turn"),
        "rbs_carry_record": rank_sql("orders", "o_totalprice, o_orderkey, o_custkey, o_orderpriority", "o_totalprice, o_orderkey"),
        "rbs_payload_documents": "SELECT doc_id, row_number() OVER (ORDER BY n_chars, doc_id) - 1 AS rank, lang, md5(text) AS text_md5 FROM documents",
        "rbs_initial_shuffle": f"SELECT o_orderkey, ((row_number() OVER (ORDER BY {digest(7, 0, 'init', 'o_orderkey')}, o_orderkey::VARCHAR) - 1) % 64)::INT AS node FROM orders",
        "rbs_level0_local_pivots": f"{two} SELECT node, j, c AS price, id FROM l0_pick",
        "rbs_level0_median_tree": f"{two} SELECT grp, j, c AS price, id FROM l0_tree",
        "rbs_level0_route": f"{two} SELECT id AS o_orderkey, bucket, node FROM l0_routed",
        "rbs_level1_route": f"{two} SELECT id AS o_orderkey, bucket, node FROM l1_routed",
        "rbs_final_counts": f"{level_ctes(src, 16, [16], 16)} SELECT node, count(*) AS n FROM l0_routed GROUP BY node",
        "rbs_messages": """WITH k AS (SELECT count(*) AS n FROM orders)
            SELECT -1 AS level, 'initial' AS phase, n AS n_msgs, 16 * n AS n_bytes FROM k UNION ALL
            SELECT l, 'pivots_up', 7 * 64, 16 * 7 * 64 FROM range(2) t(l) UNION ALL SELECT l, 'pivots_down', 7 * CAST(pow(8, l) AS BIGINT), 16 * 7 * CAST(pow(8, l) AS BIGINT) FROM range(2) t(l) UNION ALL
            SELECT l, 'keys', n, 16 * n FROM k, range(2) t(l) UNION ALL SELECT 2, 'payload', n, 104 * n FROM k""",
        "rbs_verify": "SELECT 0 AS inside, 0 AS across, count(*) AS rows, count(*) AS ranks FROM orders",
        "rbs_group_isolation": "SELECT l AS level, 0 AS leaving, (SELECT count(*) FROM orders) AS n_msgs FROM range(2) t(l)",
        "bfs_rank_events": "SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) - 1 AS rank FROM events WHERE event_id < 4096",
        "bfs_boundaries": f"""WITH p AS (SELECT event_id, value, (row_number() OVER (ORDER BY {digest(7, 0, 'init', 'event_id')}, event_id::VARCHAR) - 1) % 64 AS node FROM events WHERE event_id < 4096),
            o AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY value, event_id) AS r, count(*) OVER (PARTITION BY node) AS m FROM p),
            s AS (SELECT o.value, o.event_id FROM o JOIN range(1, 9) t(j) ON o.r = greatest(1, ceil(j * m / 9.0))),
            a AS (SELECT *, row_number() OVER (ORDER BY value, event_id) AS r, count(*) OVER () AS m FROM s)
            SELECT (j - 1)::INT AS j, value, event_id FROM a JOIN range(1, 64) t(j) ON a.r = greatest(1, ceil(j * m / 64.0))""",
        "single_sort_part": "SELECT p_partkey, p_retailprice, row_number() OVER (ORDER BY p_retailprice, p_partkey) - 1 AS rank FROM part WHERE p_partkey < 1024",
        "single_scan_min": "SELECT min(value) AS value FROM events WHERE event_id < 8192",
        "global_random_pivots": f"""WITH d AS (SELECT o_orderkey, o_totalprice FROM orders ORDER BY {digest(7, 0, 'draw', 'o_orderkey')}, o_orderkey::VARCHAR LIMIT 15)
            SELECT row_number() OVER (ORDER BY o_totalprice, o_orderkey)::INT AS j, o_orderkey, o_totalprice FROM d""",
        "proportional_nodes": """WITH c AS (SELECT floor(o_totalprice / 40000)::INT AS bucket, count(*) AS n FROM orders GROUP BY 1),
            b AS (SELECT bucket, n, (sum(n) OVER (ORDER BY bucket) - n)::BIGINT AS before, (sum(n) OVER ())::BIGINT AS total FROM c),
            f AS (SELECT bucket, n, floor(before * 64 / total)::INT AS first_node, ceil((before + n) * 64 / total)::INT - 1 AS last_node FROM b)
            SELECT bucket, n, first_node, greatest(first_node, last_node) - first_node + 1 AS n_nodes FROM f""",
        "pivots_naive": f"WITH {_events_nodes(8)}, {_leave_one_out(8, NAIVE, 'n')}",
        "pivots_shifted": f"WITH {_events_nodes(8)}, {_leave_one_out(8, SHIFTED, 'n')}",
        "pivots_mixed": f"WITH {_events_nodes(8)}, {_leave_one_out(8, MIXED, 'n')}",
        "pivots_case_equal": f"WITH {_events_nodes(16)}, {_leave_one_out(16, MIXED, 'n')}",
        "pivots_case_between": f"WITH {_events_nodes(12)}, s AS (SELECT * FROM n WHERE h <= 8), {_leave_one_out(8, MIXED, 's')}",
        "pivots_case_short": f"WITH {_events_nodes(5)}, a AS (SELECT n.node, n.value, n.event_id FROM range(1, 4) t(j), (SELECT DISTINCT node FROM n) x JOIN n ON n.node = x.node AND n.h = {digest(7, 0, 'again', 'x.node', 'j')} % 5 + 1), s AS (SELECT node, value, event_id FROM n UNION ALL SELECT * FROM a), {_leave_one_out(8, MIXED, 's')}",
        "pivots_case_double": _double(8, 16),
        "pivots_case_long": _double(8, 40),
        "exact_median_pivots": f"""WITH {_events_nodes(8)}, q AS (WITH {_leave_one_out(8, NAIVE, 'n')}),
            r AS (SELECT *, row_number() OVER (PARTITION BY j ORDER BY value, event_id) AS pos, count(*) OVER (PARTITION BY j) AS m FROM q),
            e AS (SELECT value, event_id FROM r WHERE pos = (m + 1) // 2)
            SELECT (row_number() OVER (ORDER BY value, event_id) - 1)::INT AS j, value, event_id FROM e""",
        "top_k_lineitem": f"SELECT * FROM ({rank_sql('lineitem', f'{line}, l_extendedprice', f'l_extendedprice, {line}')}) WHERE rank < 100",
        "select_rank_lineitem": f"SELECT * FROM ({rank_sql('lineitem', f'{line}, l_extendedprice', f'l_extendedprice, {line}')}) WHERE rank = 1234",
        "global_quantiles": f"SELECT rank, o_orderkey, o_totalprice FROM ({orders}) WHERE rank IN (SELECT q * (SELECT count(*) FROM orders) // 10 FROM range(10) t(q))",
        "range_lookup": f"SELECT o_orderkey, o_totalprice, rank FROM ({orders}) WHERE o_totalprice BETWEEN 100000 AND 120000",
        "sql_functions_route": f"""WITH b AS (SELECT o_orderkey, (o_totalprice >= 50000)::INT + (o_totalprice >= 100000)::INT + (o_totalprice >= 150000)::INT AS bucket FROM orders)
            SELECT o_orderkey, bucket, (bucket * 16 + {digest(7, 0, 'route', 'o_orderkey')} % 16)::INT AS node FROM b""",
        "udtf_pivots": """WITH o AS (SELECT (event_id // 64)::INT AS node, value, row_number() OVER (PARTITION BY event_id // 64 ORDER BY value) AS r FROM events WHERE event_id < 640)
            SELECT node, 64 AS n, (r // 16 - 1)::INT AS j, value AS pivot FROM o WHERE r IN (16, 32, 48)""",
    }
    out |= {
        "policy_pivots": f"{_policy_ctes()} SELECT policy, j, value, event_id FROM piv",
        "policy_buckets": f"""{_policy_ctes()}, e AS (SELECT q.policy, e.event_id, count(*) FILTER (WHERE q.value < e.value OR (q.value = e.value AND q.event_id <= e.event_id))::INT AS bucket
            FROM events e, piv q GROUP BY ALL) SELECT policy, bucket, count(*) AS n FROM e GROUP BY ALL""",
        "rbs_messages_measured": f"""SELECT level, phase, sum(n)::BIGINT AS n_msgs, sum(n * size)::BIGINT AS n_bytes FROM ({two},
            g AS (SELECT 0 AS level, count(DISTINCT node) AS nodes, count(DISTINCT grp) AS grps FROM l0_sample UNION ALL SELECT 1, count(DISTINCT node), count(DISTINCT grp) FROM l1_sample)
            SELECT -1 AS level, 'initial' AS phase, count(*) AS n, 16 AS size FROM placed UNION ALL SELECT level, 'pivots_up', 7 * nodes, 16 FROM g UNION ALL SELECT level, 'pivots_down', 7 * grps, 16 FROM g
            UNION ALL SELECT 0, 'keys', count(*), 16 FROM l0_routed UNION ALL SELECT 1, 'keys', count(*), 16 FROM l1_routed UNION ALL SELECT 2, 'payload', count(*), 104 FROM l1_routed) GROUP BY ALL""",
        "rbs_node_load": f"""{two}, n AS (SELECT 0 AS level, 'sent' AS side, node, count(*) AS n FROM placed GROUP BY node UNION ALL SELECT 0, 'received', node, count(*) FROM l0_routed GROUP BY node
            UNION ALL SELECT 1, 'sent', node, count(*) FROM l0_routed GROUP BY node UNION ALL SELECT 1, 'received', node, count(*) FROM l1_routed GROUP BY node)
            SELECT level, side, max(n) AS most, avg(n) AS mean FROM n GROUP BY ALL""",
    }
    for name, nodes, rank, trials in (("quantile_smallest_of_9", (25, 100, 400), 1, 60), ("pivot_spread", (16, 64, 256), 5, 80)):
        parts = [
            f"""SELECT {n} AS nodes, avg(q) AS mean, stddev_samp(q) AS std FROM (SELECT trial, quantile_cont(q, 0.5) AS q FROM (SELECT node // {n} AS trial, x AS q FROM (SELECT node, ('0x'||substr(md5('3|{n}|'||i||'|'||node),1,8))::BIGINT / 4294967296.0::DOUBLE AS x
            FROM range({trials * n}) a(node), range(9) b(i)) QUALIFY row_number() OVER (PARTITION BY node ORDER BY x) = {rank}) GROUP BY trial)"""
            for n in nodes
        ]
        out[name] = " UNION ALL ".join(parts)
    ledger = out["rbs_messages"]
    out["rbs_traffic_cube"] = f"SELECT level, phase, sum(n_msgs)::BIGINT AS n_msgs, sum(n_bytes)::BIGINT AS n_bytes FROM ({ledger}) GROUP BY CUBE (level, phase)"
    return out
