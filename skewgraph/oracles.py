"""The graph queries' results in DuckDB's SQL, written from their definitions."""

from __future__ import annotations

from . import relational
from .functions.measures import COMPLEXITY
from .queries import SEARCH_VIEWS, SOURCES, SSSP_VIEWS, STATS_VIEWS, STEPS, SWITCH, VARIANTS, WORKERS
from .streaming import batches

BOTH = "SELECT src, dst, w FROM one UNION ALL SELECT dst, src, w FROM one"
VIEWS = {
    "part_next": """SELECT src, dst, min(w) AS w FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey
        ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity) AS dst, CAST(l_quantity AS BIGINT) AS w FROM lineitem)
        WHERE dst IS NOT NULL AND src <> dst GROUP BY src, dst""",
    "supplier_part": f"WITH one AS (SELECT DISTINCT l_suppkey AS src, 1000000000 + l_partkey AS dst, CAST(1 AS BIGINT) AS w FROM lineitem) {BOTH}",
    "order_part": f"WITH one AS (SELECT l_orderkey AS src, 1000000000 + l_partkey AS dst, min(CAST(l_quantity AS BIGINT)) AS w FROM lineitem GROUP BY 1, 2) {BOTH}",
    "event_hub": f"""WITH one AS (SELECT event_id AS src, 2000000000 + dense_rank() OVER (ORDER BY event_type) AS dst, CAST(1 AS BIGINT) AS w FROM events
        UNION ALL SELECT event_id, 1000000000 + user_id, 1 FROM events) {BOTH}""",
    "event_lattice": f"""WITH one AS (SELECT src, dst, CAST(1 AS BIGINT) AS w FROM (
        SELECT event_id AS src, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS dst FROM events UNION
        SELECT event_id, lead(event_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) FROM events) WHERE dst IS NOT NULL)
        SELECT DISTINCT * FROM ({BOTH})""",
    "part_grid": f"""WITH n AS (SELECT count(*) AS n, CAST(ceil(sqrt(count(*))) AS BIGINT) AS width FROM part),
        one AS (SELECT p_partkey AS src, p_partkey + 1 AS dst, CAST(p_size AS BIGINT) AS w FROM part, n WHERE (p_partkey + 1) % width <> 0 AND p_partkey + 1 < n
        UNION ALL SELECT p_partkey, p_partkey + width, p_size FROM part, n WHERE p_partkey + width < n) {BOTH}""",
    "fk_entities": f"""WITH one AS (SELECT DISTINCT src, dst, CAST(1 AS BIGINT) AS w FROM (
        SELECT 'r' || n_regionkey AS src, 'n' || n_nationkey AS dst FROM nation UNION ALL SELECT 'n' || c_nationkey, 'c' || c_custkey FROM customer UNION ALL
        SELECT 'n' || s_nationkey, 's' || s_suppkey FROM supplier UNION ALL SELECT 'c' || o_custkey, 'o' || o_orderkey FROM orders UNION ALL
        SELECT 'o' || l_orderkey, 'p' || l_partkey FROM lineitem UNION ALL SELECT 's' || l_suppkey, 'p' || l_partkey FROM lineitem)) {BOTH}""",
    "token_bigram": """WITH t AS (SELECT string_split(text, ' ') AS t FROM documents),
        p AS (SELECT unnest(list_zip(t[1:len(t) - 1], t[2:])) AS p FROM t WHERE len(t) > 1)
        SELECT p[1] AS src, p[2] AS dst, count(*) AS w FROM p WHERE p[1] <> '' AND p[2] <> '' GROUP BY 1, 2""",
    "page_paths": """SELECT DISTINCT 'page:' || page_id AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst, CAST(1 AS BIGINT) AS w FROM pages""",
    "turn_chain": """SELECT conv_id * 1000 + turn AS src, conv_id * 1000 + nxt AS dst, CAST(1 AS BIGINT) AS w FROM (
        SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL""",
}


def base(view: str) -> str:
    """CTEs ``e`` (edges), ``d`` (every node's outdegree), ``m`` (greatest degree, threshold)."""
    return f"""e AS MATERIALIZED ({VIEWS[view]}),
d AS MATERIALIZED (SELECT node, CAST(sum(x) AS BIGINT) AS deg FROM (SELECT src AS node, 1 AS x FROM e UNION ALL SELECT dst, 0 FROM e) GROUP BY node),
mx AS (SELECT max(deg) AS most FROM d),
bins AS (SELECT greatest(1, CAST(ceil(deg * 10 / greatest(most, 1)) AS BIGINT)) AS bin, count(*) AS n FROM d, mx GROUP BY 1),
m AS (SELECT greatest(1, bin * most // 10) AS mdt FROM bins, mx ORDER BY n DESC, bin DESC LIMIT 1)"""


def literal(view: str) -> str:
    s = SOURCES.get(view, 0)
    return f"'{s}'" if isinstance(s, str) else f"CAST({s} AS BIGINT)"


def bfs(view: str, most: int | None = None) -> str:
    """CTE ``lv`` (node, level); ends by ``most``, at the latest after 60 levels."""
    return f"""walk AS (SELECT {literal(view)} AS node, CAST(0 AS BIGINT) AS level UNION
  SELECT e.dst, walk.level + 1 FROM walk JOIN e ON e.src = walk.node WHERE walk.level < {most or 60}),
lv AS MATERIALIZED (SELECT node, min(level) AS level FROM walk GROUP BY node)"""


def keyed(view: str, step: str, better: str, start: str, most: int | None = None) -> str:
    """CTE ``st`` (node, value) by keyed recursion; ``step``: the value handed on, ``better``: against the old one."""
    limit = f" AND st.k < {most}" if most else ""
    return f"""st(node, value, k) USING KEY (node) AS (SELECT {literal(view)}, CAST({start} AS BIGINT), 0 UNION
  SELECT e.dst, {'min' if better == '<' else 'max'}({step}), max(st.k) + 1 FROM st JOIN e ON e.src = st.node LEFT JOIN recurring.st AS old ON old.node = e.dst
  WHERE (old.node IS NULL OR {step} {better} old.value){limit} GROUP BY e.dst)"""


FRONT = f"f AS (SELECT level + 1 AS superstep, node, deg FROM lv JOIN d USING (node) WHERE level < {STEPS} AND deg > 0)"
SLICES = "sl AS (SELECT superstep, node, deg, unnest(range(0, CAST(ceil(deg / mdt) AS BIGINT))) AS launch, mdt FROM f, m)"


def sublist_ctes(switch: int) -> str:
    return f"""{SLICES},
sz AS (SELECT superstep, launch, count(*) AS size, CAST(sum(least(mdt, deg - launch * mdt)) AS BIGINT) AS slice, CAST(sum(deg - launch * mdt) AS BIGINT) AS rest FROM sl GROUP BY 1, 2),
sw AS (SELECT superstep, min(launch) FILTER (WHERE size < {switch}) AS switch FROM sz GROUP BY 1)"""


def loads(strategy: str) -> str:
    """SELECT of superstep, launch, worker, load from the CTEs before."""
    t = WORKERS
    even = "SELECT superstep, launch, t + 1 AS worker, CAST({load} AS BIGINT) AS load FROM ({total}), (SELECT unnest(range(0, " + str(t) + ")) AS t) WHERE {load} > 0"
    block, single = f"least(ceil(a / {t}), a - t * ceil(a / {t}))", f"(a - t + {t - 1}) // {t}"
    whole = "SELECT superstep, CAST(0 AS BIGINT) AS launch, sum(deg) AS a FROM f GROUP BY 1"
    dealt = "SELECT superstep, launch, (r - 1) % " + str(t) + " + 1 AS worker, CAST(sum(x) AS BIGINT) AS load FROM ({rows}) GROUP BY 1, 2, 3"
    if strategy == "EP":
        return even.format(load=single, total=whole)
    if strategy == "WD":
        return even.format(load=block, total=whole)
    if strategy == "BS":
        return dealt.format(rows="SELECT superstep, CAST(0 AS BIGINT) AS launch, deg AS x, row_number() OVER (PARTITION BY superstep ORDER BY node) AS r FROM f")
    if strategy == "NS":
        parts = """SELECT superstep, node, deg, greatest(1, CAST(ceil(deg / mdt) AS BIGINT)) AS parts FROM f, m"""
        rows = f"""SELECT superstep, node, c, CAST(ceil((c + 1) * deg / parts) - ceil(c * deg / parts) AS BIGINT) AS x FROM (SELECT *, unnest(range(0, parts)) AS c FROM ({parts}))"""
        return dealt.format(rows=f"SELECT superstep, CAST(0 AS BIGINT) AS launch, x, row_number() OVER (PARTITION BY superstep ORDER BY node, c) AS r FROM ({rows})")
    rows = "SELECT superstep, launch, least(mdt, deg - launch * mdt) AS x, row_number() OVER (PARTITION BY superstep, launch ORDER BY node) AS r FROM sl JOIN sw USING (superstep) WHERE switch IS NULL OR launch < switch"
    tail = "SELECT superstep, launch, rest AS a FROM sz JOIN sw USING (superstep) WHERE launch = switch"
    return dealt.format(rows=rows) + " UNION ALL " + even.format(load=block, total=tail)


def _with(*ctes: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n"


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for v in STATS_VIEWS:
        b = _with(base(v))
        out[f"graph_stats_{v}"] = b + """SELECT count(*) AS n_nodes, CAST(sum(deg) AS BIGINT) AS n_edges, max(deg) AS max_deg, round(sum(deg) / CAST(count(*) AS DOUBLE), 6) AS avg_deg,
          round(sqrt(CAST(count(*) AS DOUBLE) * CAST(sum(deg * deg) AS DOUBLE) - CAST(sum(deg) AS DOUBLE) * CAST(sum(deg) AS DOUBLE)) / count(*), 4) AS std_deg,
          round(sqrt(CAST(sum(deg * deg) AS DOUBLE) / count(*)), 4) AS rms_deg, CAST(count(*) FILTER (WHERE deg = 0) AS BIGINT) AS sinks FROM d"""
        out[f"outdegree_hist_{v}"] = b + "SELECT deg, count(*) AS n_nodes FROM d GROUP BY deg"
        out[f"degree_bins_{v}"] = b + "SELECT i AS bin, (i - 1) * most // 10 AS lo, i * most // 10 AS hi, coalesce(n, 0) AS n_nodes FROM mx, (SELECT unnest(range(1, 11)) AS i) LEFT JOIN bins ON bin = i"
        report = """SELECT {rule} AS rule, max(most) AS max_deg, CAST(max(mdt) AS BIGINT) AS mdt, CAST(count(*) FILTER (WHERE deg > mdt) AS BIGINT) AS n_split,
          CAST(sum(greatest(1, ceil(deg / mdt)) - 1) AS BIGINT) AS n_children, count(*) FILTER (WHERE deg > mdt) * 1000 // count(*) AS split_permille FROM d, mx, {m}"""
        out[f"mdt_{v}"] = b + report.format(rule="'auto'", m="m")
        if f"mdt_rules_{v}" not in out and v in ("part_next", "supplier_part", "order_part", "event_hub"):
            rules = {"'auto'": "m", "'max'": "(SELECT most AS mdt FROM mx)", "'max_minus_avg'": "(SELECT greatest(1, max(deg) - CAST(sum(deg) AS BIGINT) // count(*)) AS mdt FROM d)", "'constant'": "(SELECT 5 AS mdt)"}
            out[f"mdt_rules_{v}"] = b + " UNION ALL ".join(report.format(rule=r, m=m) for r, m in rules.items())
            split = """sp AS (SELECT node AS parent, c AS child_no, CAST(ceil((c + 1) * deg / parts) - ceil(c * deg / parts) AS BIGINT) AS part_deg FROM (
              SELECT *, unnest(range(0, parts)) AS c FROM (SELECT node, deg, CAST(ceil(deg / mdt) AS BIGINT) AS parts FROM d, m WHERE deg > mdt)))"""
            s = _with(base(v), split)
            out[f"ns_split_{v}"] = s + "SELECT * FROM sp"
            out[f"ns_degrees_{v}"] = s + """SELECT 'before' AS phase, deg, count(*) AS n_nodes FROM d GROUP BY deg UNION ALL
              SELECT 'after', deg, count(*) FROM (SELECT deg FROM d, m WHERE deg <= mdt UNION ALL SELECT part_deg FROM sp) GROUP BY deg"""
            out[f"ns_invariants_{v}"] = s + """, al AS (SELECT parent, part_deg FROM sp UNION ALL SELECT node, deg FROM d, m WHERE deg <= mdt AND deg > 0)
              SELECT (SELECT count(*) FROM e) AS edges_before, CAST(sum(s) AS BIGINT) AS edges_after, max(x) AS max_part_deg, max(x - n) AS max_gap
              FROM (SELECT parent, sum(part_deg) AS s, max(part_deg) AS x, min(part_deg) AS n FROM al GROUP BY parent)"""
            out[f"csr_pages_{v}"] = b + "SELECT src AS node, count(*) AS deg, count(*) AS n, CAST(sum(dst) AS BIGINT) AS sum_dst, CAST(sum(w) AS BIGINT) AS sum_w FROM e GROUP BY src"
            out[f"coo_roundtrip_{v}"] = "SELECT CAST(0 AS BIGINT) AS differing"
            out[f"scan_{v}"] = b + "SELECT node, deg, CAST(sum(deg) OVER (ORDER BY node) AS BIGINT) AS running_total FROM d WHERE deg > 0"
            out[f"wd_blocks_{v}"] = b + f"""SELECT t + 1 AS worker, node, greatest(lo, t * q) - lo AS "offset", least(hi, (t + 1) * q) - greatest(lo, t * q) AS len FROM (
              SELECT *, unnest(range(lo // q, (hi - 1) // q + 1)) AS t FROM (SELECT node, CAST(sum(deg) OVER (ORDER BY node) AS BIGINT) AS hi,
              CAST(sum(deg) OVER (ORDER BY node) - deg AS BIGINT) AS lo, (SELECT CAST(ceil(sum(deg) / {WORKERS}) AS BIGINT) FROM d) AS q FROM d WHERE deg > 0))"""
            mem = f"""s AS (SELECT count(*) AS n, CAST(sum(deg) AS BIGINT) AS e, CAST(sum(greatest(1, ceil(deg / mdt)) - 1) AS BIGINT) AS c FROM d, m),
              mw AS (SELECT 'BS' AS strategy, 3 * n + 2 * e AS words FROM s UNION ALL SELECT 'EP', 7 * e FROM s UNION ALL SELECT 'WD', 5 * n + 2 * e + {2 * WORKERS} FROM s UNION ALL
              SELECT 'NS', 4 * n + 2 * e + 3 * c FROM s UNION ALL SELECT 'HP', 5 * n + 2 * e FROM s),
              bu AS (SELECT (max(words) FILTER (WHERE strategy = 'HP') + max(words) FILTER (WHERE strategy = 'EP')) // 2 AS b FROM mw)"""
            out[f"memory_words_{v}"] = _with(base(v), mem) + "SELECT strategy, words, words <= b AS fits, CASE WHEN words <= b THEN 'runs' ELSE 'insufficient_memory' END AS status FROM mw, bu"
            out[f"rank_memory_{v}"] = _with(base(v), mem) + "SELECT strategy, words, CAST(rank() OVER (ORDER BY words) AS INTEGER) AS rank FROM mw"
    for v in ("part_next", "event_hub"):
        b = _with(base(v), bfs(v, STEPS), FRONT, sublist_ctes(SWITCH))
        for s in ("BS", "EP", "WD", "NS", "HP"):
            out[f"loads_{s.lower()}_{v}"] = b + loads(s)
        every = " UNION ALL ".join(f"SELECT '{s}' AS strategy, superstep, launch, max(load) AS most, sum(load) AS load FROM ({loads(s)}) GROUP BY 2, 3" for s in ("BS", "EP", "WD", "NS", "HP"))
        out[f"balance_{v}"] = b + f"""SELECT strategy, superstep, CAST(sum(most) AS BIGINT) AS makespan, CAST(sum(load) AS BIGINT) AS total,
          CAST(sum(most) * 1000 * {WORKERS} // sum(load) AS BIGINT) AS imbalance_permille FROM ({every}) GROUP BY 1, 2"""
        report = """SELECT superstep, launch, size, CASE WHEN launch = switch THEN rest ELSE slice END AS edges, CASE WHEN launch = switch THEN 'block' ELSE 'sub' END AS mode
          FROM sz JOIN sw USING (superstep) WHERE switch IS NULL OR launch <= switch"""
        out[f"hp_sublists_{v}"] = b + report
        out[f"hp_noswitch_{v}"] = _with(base(v), bfs(v, STEPS), FRONT, sublist_ctes(0)) + report
        out[f"ep_pushes_{v}"] = b + f""", h AS (SELECT a.level + 1 AS superstep, e.dst AS node, count(*) AS times FROM e JOIN lv a ON a.node = e.src JOIN lv c ON c.node = e.dst
          WHERE c.level = a.level + 1 AND a.level < {STEPS} GROUP BY 1, 2)
          SELECT superstep, CAST(sum(times * deg) AS BIGINT) AS edge_pushes, CAST(sum(times) AS BIGINT) AS chunk_pushes, count(*) AS nodes, CAST(sum(times * deg) AS BIGINT) AS raw, CAST(sum(deg) AS BIGINT) AS condensed
          FROM h JOIN d USING (node) GROUP BY 1"""
        full = _with(base(v), bfs(v, 12))
        out[f"bfs_parents_{v}"] = full + """SELECT lv.node, lv.level, coalesce(min(p.node), -1) AS parent FROM lv LEFT JOIN (e JOIN lv p ON p.node = e.src) ON e.dst = lv.node AND p.level = lv.level - 1 GROUP BY 1, 2"""
        out[f"level_sizes_{v}"] = full + "SELECT level, count(*) AS n_nodes, CAST(sum(deg) AS BIGINT) AS active_edges FROM lv JOIN d USING (node) GROUP BY 1"
    for v in SEARCH_VIEWS:
        for s in ("bs", "ep", "wd", "ns", "hp"):
            out[f"bfs_{s}_{v}"] = _with(base(v), bfs(v, 12)) + "SELECT node, level FROM lv"
    hops = lambda v: _with(base(v), keyed(v, "st.value + 1", "<", "0")) + "SELECT node, value AS level FROM st"
    paths = lambda v: _with(base(v), keyed(v, "st.value + e.w", "<", "0")) + "SELECT node, value AS dist FROM st"
    for v in SSSP_VIEWS:
        for s in ("bs", "ep", "wd", "ns", "hp"):
            out[f"sssp_{s}_{v}"] = paths(v)
            out[f"bfs_{s}_event_lattice"] = hops("event_lattice")
    out["bfs_wd_part_grid"], out["bfs_ep_fk_entities"], out["bfs_ep_token_bigram"], out["sssp_hp_token_bigram"] = hops("part_grid"), hops("fk_entities"), hops("token_bigram"), paths("token_bigram")
    for name, (program, _, v, _) in VARIANTS.items():
        out[name] = hops(v) if program == "bfs" else paths(v)
    for v in ("part_next", "event_hub"):
        full = _with(base(v), bfs(v, 12))
        pushed = "SELECT level AS superstep, CAST(sum(deg) AS BIGINT) AS single_pushes, count(*) AS chunk_pushes FROM lv JOIN d USING (node) WHERE level > 0 GROUP BY 1"
        out[f"ep_chunking_{v}"] = full + pushed
        out[f"run_metrics_{v}"] = full + """SELECT a.level + 1 AS superstep, a.n AS frontier, b.n AS improved, a.e AS active_edges, a.e AS relaxations
          FROM (SELECT level, count(*) FILTER (WHERE deg > 0) AS n, CAST(sum(deg) AS BIGINT) AS e FROM lv JOIN d USING (node) GROUP BY 1) a JOIN (SELECT level, count(*) AS n FROM lv GROUP BY 1) b ON b.level = a.level + 1"""
        out[f"tasks_hold_workers_{v}"] = "SELECT s AS strategy, CAST(0 AS BIGINT) AS mixed FROM (SELECT unnest(['BS', 'EP', 'WD', 'NS', 'HP']) AS s)"
        out[f"wd_range_join_{v}"] = out.get(f"wd_blocks_{v}") or ""
        words = out[f"memory_words_{v}"]
        ease = " UNION ALL ".join(f"SELECT '{k}' AS strategy, {e} AS ease" for k, e in COMPLEXITY.items())
        out[f"rank_strategies_{v}"] = f"""SELECT strategy, CAST(rank() OVER (ORDER BY makespan) AS INTEGER) AS time_rank, CAST(rank() OVER (ORDER BY words) AS INTEGER) AS memory_rank, CAST(rank() OVER (ORDER BY ease) AS INTEGER) AS ease_rank
          FROM (SELECT strategy, sum(makespan) AS makespan FROM ({out[f"balance_{v}"]}) GROUP BY 1) JOIN ({words}) USING (strategy) JOIN ({ease}) USING (strategy)"""
    out["loads_per_node_event_hub"] = _with(base("event_hub"), bfs("event_hub", STEPS), FRONT) + "SELECT superstep, max(deg) AS makespan, count(*) AS workers FROM f GROUP BY 1"
    for s in ("BS", "WD"):
        out[f"load_cv_{s.lower()}_event_hub"] = _with(base("event_hub"), bfs("event_hub", STEPS), FRONT, sublist_ctes(SWITCH)) + f"""SELECT superstep, launch,
          CAST(floor(1000 * sqrt(CAST({WORKERS} * sum(load * load) - sum(load) * sum(load) AS DOUBLE)) / sum(load)) AS BIGINT) AS cv_permille FROM ({loads(s)}) GROUP BY 1, 2"""
    out["udaf_gini_load"] = _with(base("event_hub")) + """SELECT round((sum(x * (2 * i - n - 1))) / (max(n) * sum(x)), 6) AS gini
      FROM (SELECT CAST(deg AS DOUBLE) AS x, row_number() OVER (ORDER BY deg) AS i, CAST(count(*) OVER () AS DOUBLE) AS n FROM d WHERE deg > 0)"""
    out["bfs_multi_part_next"] = _with(base("part_next"), bfs("part_next", 12).replace("SELECT CAST(0 AS BIGINT) AS node, CAST(0 AS BIGINT) AS level", "SELECT CAST(i AS BIGINT) AS node, CAST(0 AS BIGINT) AS level FROM range(3) r(i)")) + "SELECT node, level FROM lv"
    out["neighbour_median_part_next"] = _with(base("part_next")) + "SELECT node, coalesce(quantile_cont(CAST(src AS DOUBLE), 0.5), CAST(node AS DOUBLE)) AS value FROM d LEFT JOIN e ON dst = node GROUP BY node"
    out["weighted_sum_part_next"] = _with(base("part_next")) + "SELECT node, CAST(coalesce(sum(src * w), node) AS BIGINT) AS value FROM d LEFT JOIN e ON dst = node GROUP BY node"
    out["betweenness_turn_chain"] = """SELECT conv_id * 1000 + turn AS node, CAST((i - 1) * (n - i) AS DOUBLE) AS score FROM (
      SELECT conv_id, turn, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS i, count(*) OVER (PARTITION BY conv_id) AS n FROM conversations) WHERE n > 1"""
    shares = ["s12 AS (SELECT node, paths, CAST(0 AS DOUBLE) AS score FROM p WHERE level = 12)"]
    shares += [f"s{k} AS (SELECT p.node, p.paths, coalesce(sum(p.paths / n.paths * (1 + n.score)), 0) AS score FROM p LEFT JOIN (e JOIN s{k + 1} n ON e.dst = n.node) ON e.src = p.node WHERE p.level = {k} GROUP BY 1, 2)" for k in reversed(range(12))]
    counted = "p AS (SELECT CAST(0 AS BIGINT) AS node, CAST(0 AS BIGINT) AS level, CAST(1 AS DOUBLE) AS paths UNION ALL SELECT e.dst, max(lv.level), sum(p.paths) FROM p JOIN e ON e.src = p.node JOIN lv ON lv.node = e.dst AND lv.level = p.level + 1 GROUP BY e.dst)"
    every = " UNION ALL ".join(f"SELECT node, score FROM s{k}" for k in range(13))
    out["dependencies_part_next"] = _with(base("part_next"), bfs("part_next", 12), counted, *shares) + f"SELECT node, round(coalesce(CASE WHEN node <> 0 THEN score END, 0), 6) AS score FROM d LEFT JOIN ({every}) USING (node)"
    out["components_event_hub"] = f"{_with(base('event_hub'))} SELECT node, CAST(0 AS BIGINT) AS label FROM d"
    out["widest_supplier_part"] = f"{_with(base('supplier_part'))} SELECT node, CAST(1 AS BIGINT) AS width FROM d WHERE node <> 0"
    out["strategies_agree_supplier_part"] = "SELECT 'BS-' || s AS pair, CAST(0 AS BIGINT) AS differing FROM (SELECT unnest(['EP', 'WD', 'NS', 'HP']) AS s)"
    out["distributive_check"] = """WITH x AS (SELECT CAST(l_linenumber AS BIGINT) AS a, CAST(l_quantity AS BIGINT) AS b, CAST(l_suppkey AS BIGINT) AS w FROM lineitem)
      SELECT 'min_plus' AS program, count(*) AS samples, count(*) FILTER (WHERE least(a, b) + w <> least(a + w, b + w)) AS violations FROM x UNION ALL
      SELECT 'max_min', count(*), count(*) FILTER (WHERE least(greatest(a, b), w) <> greatest(least(a, w), least(b, w))) FROM x UNION ALL
      SELECT 'mean', count(*), count(*) FILTER (WHERE (a + b) // 2 * w % 5 <> (a * w % 5 + b * w % 5) // 2) FROM x"""
    suppliers = "d AS MATERIALIZED (SELECT l_suppkey AS node, count(*) AS deg FROM lineitem GROUP BY 1), f AS (SELECT CAST(1 AS BIGINT) AS superstep, node, deg FROM d)"
    sublists = lambda mdt, switch: _with(suppliers, f"m AS (SELECT {mdt} AS mdt)", sublist_ctes(switch))
    kept = "FROM sz JOIN sw USING (superstep) WHERE switch IS NULL OR launch <= switch"
    out["wd_blocks_example"] = _with(suppliers) + """SELECT t + 1 AS worker, node, greatest(lo, t * q) - lo AS "offset", least(hi, (t + 1) * q) - greatest(lo, t * q) AS len FROM (
      SELECT *, unnest(range(lo // q, (hi - 1) // q + 1)) AS t FROM (SELECT node, CAST(sum(deg) OVER (ORDER BY node) AS BIGINT) AS hi,
      CAST(sum(deg) OVER (ORDER BY node) - deg AS BIGINT) AS lo, (SELECT CAST(ceil(sum(deg) / 4) AS BIGINT) FROM d) AS q FROM d))"""
    out["ns_split_example"] = _with(suppliers) + """SELECT node AS parent, c AS child_no, CAST(ceil((c + 1) * deg / parts) - ceil(c * deg / parts) AS BIGINT) AS part_deg FROM (
      SELECT *, unnest(range(0, parts)) AS c FROM (SELECT node, deg, CAST(ceil(deg / 64) AS BIGINT) AS parts FROM d WHERE deg > 64))"""
    out["hp_sublists_example"] = sublists(50, 0) + f"SELECT superstep, launch, size, CASE WHEN launch = switch THEN rest ELSE slice END AS edges, CASE WHEN launch = switch THEN 'block' ELSE 'sub' END AS mode {kept}"
    out["hp_tail_example"] = " UNION ALL ".join(f"SELECT * FROM ({sublists(5, s)} SELECT count(*) AS launches, CAST({s} AS BIGINT) AS switch_below {kept})" for s in (0, 1024))
    num = lambda *p: "('0x' || substr(md5(concat_ws(':', '42', " + ", ".join(p) + ")), 1, 8))::BIGINT"
    bit = lambda lvl: num("i", f"'{lvl}'") + " % 100"
    src = " + ".join(f"(CASE WHEN {bit(x)} >= 76 THEN {1 << (7 - x)} ELSE 0 END)" for x in range(8))
    dst = " + ".join(f"(CASE WHEN ({bit(x)} >= 57 AND {bit(x)} < 76) OR {bit(x)} >= 95 THEN {1 << (7 - x)} ELSE 0 END)" for x in range(8))
    out["gen_rmat"] = f"SELECT CAST({src} AS BIGINT) AS src, CAST({dst} AS BIGINT) AS dst, {num('i', chr(39) + 'w' + chr(39))} % 50 + 1 AS w FROM (SELECT o_orderkey AS i FROM orders)"
    s, d, w = (num("i", f"'{x}'") for x in "sdw")
    out["gen_er"] = f"SELECT {s} % 256 AS src, {d} % 256 AS dst, {w} % 50 + 1 AS w FROM (SELECT o_orderkey AS i FROM orders)"
    out["gen_lattice"] = f"""WITH r AS (SELECT event_id AS i, count(*) OVER () AS n FROM events),
      n AS (SELECT i AS a, i + 1 AS b FROM r WHERE (i + 1) % 512 <> 0 AND i + 1 < n UNION ALL SELECT i, i + 512 FROM r WHERE i + 512 < n),
      one AS (SELECT a AS src, b AS dst, {num('a', 'b')} % 50 + 1 AS w FROM n) {BOTH}"""
    out["udtf_split_node"], out["udtf_frontier_blocks"] = out["ns_split_part_next"], out["wd_blocks_example"]
    for name in ("tasks_hold_workers_part_next", "rank_strategies_part_next"):
        out.pop(name, None)
    return out | relational.oracle_sql() | batches.oracle_sql()
