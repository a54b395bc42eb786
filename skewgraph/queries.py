"""Registered queries of the graph engine."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import generators, relational
from .functions import loads as ld
from .functions import measures as ms
from .functions import tables
from .graph import Graph, to_edges
from .operators import extras, programs, scan
from .operators.strategies import Options, blocks, split_edges, split_map
from .plans import engine
from .sources import table
from .streaming import batches
from .views import VIEWS

Query = Callable[[SparkSession, str], DataFrame]
WORKERS, SWITCH, STEPS = 8, 8, 3
STATS_VIEWS = tuple(v for v in VIEWS if v != "embedding_knn")
SEARCH_VIEWS = ("part_next", "supplier_part", "event_hub")
SSSP_VIEWS = ("part_next", "order_part", "supplier_part", "event_hub", "part_grid")
SOURCES = {"token_bigram": "the", "fk_entities": "c0"}
#: Searches with other options, each with the result of the usual ones.
VARIANTS = {
    "bfs_bs_hash_event_hub": ("bfs", "BS", "event_hub", {"assign": "hash"}),
    "bfs_bs_per_node_event_hub": ("bfs", "BS", "event_hub", {"workers": "per_node"}),
    "bfs_ep_single_event_hub": ("bfs", "EP", "event_hub", {"chunked": False}),
    "sssp_ep_single_part_next": ("sssp", "EP", "part_next", {"chunked": False}),
    "bfs_ep_never_event_hub": ("bfs", "EP", "event_hub", {"condense": "never"}),
    "sssp_ep_never_part_next": ("sssp", "EP", "part_next", {"condense": "never"}),
    "sssp_hp_deep_part_next": ("sssp", "HP", "part_next", {"mdt": 5, "depth": 2, "group": 100}),
    "bfs_hp_launches_event_hub": ("bfs", "HP", "event_hub", {"fused": False}),
    "sssp_hp_noswitch_part_next": ("sssp", "HP", "part_next", {"switch_below": 0}),
    "sssp_ns_fixed_part_next": ("sssp", "NS", "part_next", {"mdt": 7}),
    "bfs_wd_pinned_event_hub": ("bfs", "WD", "event_hub", {"place": "pages"}),
    "bfs_wd_all_part_next": ("bfs", "WD", "part_next", {"data_driven": False}),
}
#: Views of long paths: all supersteps are run.
ROADS = ("part_grid", "event_lattice")


def graph(spark: SparkSession, sf_dir: str, view: str) -> Graph:
    return Graph.of(VIEWS[view](spark, sf_dir))


def source(view: str):
    return SOURCES.get(view, 0)


def _mdt(g: Graph) -> int:
    return ms.find_mdt(g.all_degrees())


def _levels(g: Graph, view: str, most: int | None = None) -> DataFrame:
    return engine.bfs(g, [source(view)], "BS", max_supersteps=most).state


def stats(view):
    return lambda spark, d: ms.graph_stats(graph(spark, d, view))


def outdegree_hist(view):
    return lambda spark, d: ms.degree_histogram(graph(spark, d, view).all_degrees())


def degree_bins(view):
    return lambda spark, d: ms.degree_bins(graph(spark, d, view).all_degrees())


def mdt(view):
    def run(spark, d):
        degrees = graph(spark, d, view).all_degrees()
        return ms.mdt_report(degrees, {"auto": ms.find_mdt(degrees)})

    return run


def mdt_rules(view):
    def run(spark, d):
        degrees = graph(spark, d, view).all_degrees()
        return ms.mdt_report(degrees, {r if isinstance(r, str) else "constant": ms.find_mdt(degrees, r) for r in ("auto", "max", "max_minus_avg", 5)})

    return run


def ns_split(view):
    def run(spark, d):
        g = graph(spark, d, view)
        return split_map(g.degrees(), _mdt(g))

    return run


def ns_degrees(view):
    def run(spark, d):
        g = graph(spark, d, view)
        m, degrees = _mdt(g), g.all_degrees()
        after = degrees.where(F.col("deg") <= m).select("deg").unionByName(split_map(g.degrees(), m).select(F.col("part_deg").alias("deg")))
        rows = [ms.degree_histogram(x).withColumn("phase", F.lit(p)) for p, x in (("before", degrees), ("after", after))]
        return rows[0].unionByName(rows[1])

    return run


def ns_invariants(view):
    def run(spark, d):
        g = graph(spark, d, view)
        parts = split_edges(g, _mdt(g)).groupBy("parent", "child_no").agg(F.count("*").alias("part_deg"))
        whole = parts.groupBy("parent").agg(F.sum("part_deg").alias("e"), F.max("part_deg").alias("most"), (F.max("part_deg") - F.min("part_deg")).alias("gap"))
        after = whole.agg(F.sum("e").alias("edges_after"), F.max("most").alias("max_part_deg"), F.max("gap").alias("max_gap"))
        return g.edges.agg(F.count("*").alias("edges_before")).join(F.broadcast(after))  # one row beside one row

    return run


def csr_pages(view):
    def run(spark, d):
        total = lambda c: F.aggregate("adj", F.lit(0).cast("long"), lambda s, e: s + e[c])
        return graph(spark, d, view).pages().groupBy("node", "deg").agg(F.sum(F.size("adj")).alias("n"), F.sum(total("dst")).alias("sum_dst"), F.sum(total("w")).alias("sum_w"))

    return run


def coo_roundtrip(view):
    def run(spark, d):
        g = graph(spark, d, view)
        back = to_edges(g.pages())
        return g.edges.exceptAll(back).unionByName(back.exceptAll(g.edges)).agg(F.count("*").alias("differing"))

    return run


def scan_query(view):
    return lambda spark, d: scan.inclusive(graph(spark, d, view).degrees(), ["node"], "deg").select("node", "deg", F.col("hi").alias("running_total"))


def wd_blocks(view):
    return lambda spark, d: blocks(graph(spark, d, view).degrees(), WORKERS).select("worker", "node", "offset", "len")


def _recorded(spark, d, view, strategy, **more) -> engine.Run:
    """The first supersteps of a search, with the edges that each worker was given."""
    return engine.bfs(graph(spark, d, view), [source(view)], strategy, options=Options(WORKERS, switch_below=SWITCH, record=True, **more), max_supersteps=STEPS)


def load_query(strategy, view, **more):
    """Edges of each worker and launch, counted in the tasks of a run."""

    def run(spark, d):
        return _recorded(spark, d, view, strategy, **more).worker_loads.groupBy("superstep", "launch", "worker").agg(F.sum("load").alias("load"))

    return run


def balance(view):
    """Makespan of each strategy's superstep, from the loads of its run."""

    def run(spark, d):
        out = None
        for s in ms.STRATEGIES:
            per_launch = ms.imbalance(load_query(s, view)(spark, d), ["superstep", "launch"], WORKERS)
            part = per_launch.groupBy("superstep").agg(F.sum("max_load").alias("makespan"), F.sum("total").alias("total")).withColumn("strategy", F.lit(s))
            out = part if out is None else out.unionByName(part)
        return out.withColumn("imbalance_permille", F.floor(F.col("makespan") * 1000 * WORKERS / F.col("total")).cast("long"))

    return run


def load_spread(strategy, view):
    """Deviation over mean of the workers' loads, launch by launch, and the Gini coefficient of all of them."""

    def run(spark, d):
        return ms.variation(load_query(strategy, view)(spark, d), ["superstep", "launch"], WORKERS)

    return run


def udaf_gini_load(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How uneven the outdegrees of a graph are."""
    return ms.gini(graph(spark, sf_dir, "event_hub").degrees(), "deg")


def tasks_hold_workers(view):
    """Tasks of a run that hold the edges of more than one worker of a launch, by strategy: none."""

    def run(spark, d):
        out = None
        for s in ms.STRATEGIES:
            per_task = _recorded(spark, d, view, s).worker_loads.groupBy("superstep", "launch", "task").agg(F.countDistinct("worker").alias("workers"))
            part = per_task.agg(F.count_if(F.col("workers") > 1).alias("mixed")).withColumn("strategy", F.lit(s))
            out = part if out is None else out.unionByName(part)
        return out

    return run


def run_metrics(view, strategy):
    """What a run counted in each superstep that improved something."""

    def run(spark, d):
        found = engine.bfs(graph(spark, d, view), [source(view)], strategy, options=Options(WORKERS, switch_below=SWITCH))
        return found.metrics.where("improved > 0").select("superstep", "frontier", "improved", "active_edges", "relaxations")

    return run


def ep_chunking(view):
    """Worklist entries pushed one by one against a node's edges at once, from two runs."""

    def run(spark, d):
        runs = [engine.bfs(graph(spark, d, view), [source(view)], "EP", options=Options(WORKERS, chunked=c)).metrics for c in (False, True)]
        single, chunk = (m.where("improved > 0").select("superstep", F.col("pushes").alias(n)) for m, n in zip(runs, ("single_pushes", "chunk_pushes"), strict=True))
        return single.join(chunk, "superstep")

    return run


def variant(program, strategy, view, **options):
    """A search with options away from the usual ones: the same result."""

    def run(spark, d):
        name = "level" if program == "bfs" else "dist"
        more = {k: options[k] for k in ("data_driven", "target") if k in options}
        own = Options(**({"workers": WORKERS, "switch_below": SWITCH} | {k: v for k, v in options.items() if k not in more}))
        return getattr(engine, program)(graph(spark, d, view), [source(view)], strategy, options=own, **more).state.select("node", F.col("value").alias(name))

    return run


def wd_range_join(view):
    """Workers' blocks found by meeting ranges instead of from running totals."""
    return lambda spark, d: blocks(graph(spark, d, view).degrees(), WORKERS, range_join=True).select("worker", "node", "offset", "len")


def multi_source(view):
    return lambda spark, d: engine.bfs(graph(spark, d, view), [0, 1, 2], "WD", options=Options(WORKERS)).state.select("node", F.col("value").alias("level"))


def gathered(program, view):
    """One round in which each node takes the aggregate of its in-neighbours' ids."""

    def run(spark, d):
        g = graph(spark, d, view)
        return engine.gather(g, program, g.nodes().select("node", F.col("node").cast("double" if program.name == "neighbour_median" else "long").alias("value")))

    return run


def forest(view):
    return lambda spark, d: extras.spanning_forest(VIEWS[view](spark, d))


def loads_per_node(view):
    """A worker for each frontier node: the greatest load of a superstep is its greatest degree."""

    def run(spark, d):
        found = engine.bfs(graph(spark, d, view), [source(view)], "BS", options=Options("per_node", record=True), max_supersteps=STEPS)
        return found.worker_loads.groupBy("superstep").agg(F.max("load").alias("makespan"), F.countDistinct("worker").alias("workers"))

    return run


def hp_sublists(view, switch_below=SWITCH):
    def run(spark, d):
        g = graph(spark, d, view)
        return ld.sublist_report(ld.frontiers(g, _levels(g, view, STEPS), STEPS), _mdt(g), switch_below)

    return run


def ep_pushes(view):
    def run(spark, d):
        g = graph(spark, d, view)
        return ld.push_report(g, _levels(g, view, STEPS), STEPS)

    return run


def memory(view):
    def run(spark, d):
        g = graph(spark, d, view)
        children = ms.mdt_report(g.all_degrees(), {"auto": _mdt(g)}).first()["n_children"]
        row = ms.graph_stats(g).first()
        words = ms.memory_words(row["n_nodes"], row["n_edges"], children, WORKERS)
        return ms.memory_frame(g, children, WORKERS, (words["HP"] + words["EP"]) // 2)

    return run


def rank_memory(view):
    def run(spark, d):
        order = F.rank().over(Window.partitionBy(F.lit(0)).orderBy("words"))  # five rows
        return memory(view)(spark, d).select("strategy", "words", order.alias("rank"))

    return run


def search(program, strategy, view):
    def run(spark, d):
        found = getattr(engine, program)(graph(spark, d, view), [source(view)], strategy, options=Options(WORKERS, switch_below=SWITCH))
        return found.state.select("node", F.col("value").alias("level" if program == "bfs" else "dist"))

    return run


def bfs_parents(view):
    def run(spark, d):
        g = graph(spark, d, view)
        return engine.with_parents(g, _levels(g, view)).select("node", F.col("value").alias("level"), F.coalesce("parent", F.lit(-1)).alias("parent"))

    return run


def level_sizes(view):
    def run(spark, d):
        g = graph(spark, d, view)
        rows = _levels(g, view).join(g.degrees(), "node", "left")
        return rows.groupBy(F.col("value").alias("level")).agg(F.count("*").alias("n_nodes"), F.sum(F.coalesce("deg", F.lit(0))).alias("active_edges"))

    return run


def components(view):
    return lambda spark, d: engine.components(graph(spark, d, view), "EP").state.select("node", F.col("value").alias("label"))


def widest(view):
    return lambda spark, d: engine.widest(graph(spark, d, view), [source(view)], "WD").state.where("step > 0").select("node", F.col("value").alias("width"))


def agree(view):
    """Rows in which another strategy's distances differ from the node-based ones, strategy by strategy."""

    def run(spark, d):
        base, out = search("sssp", "BS", view)(spark, d), None
        for s in ms.STRATEGIES[1:]:
            other = search("sssp", s, view)(spark, d)
            part = base.exceptAll(other).unionByName(other.exceptAll(base)).agg(F.count("*").alias("differing")).withColumn("pair", F.lit(f"BS-{s}"))
            out = part if out is None else out.unionByName(part)
        return out

    return run


def distributive_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Violations of distributivity over the lines' numbers: none for least sums and widest paths, some for a mean-like step."""
    mean = lambda a, b: F.floor((a + b) / 2)
    cases = {"min_plus": (programs.SSSP.extend, F.least), "max_min": (programs.WIDEST.extend, F.greatest), "mean": (lambda v, w: v * w % 5, mean)}
    a, b, w = (F.col(c).cast("long") for c in ("l_linenumber", "l_quantity", "l_suppkey"))
    counts = [F.count_if(programs.violated(e, c, a, b, w)).alias(name) for name, (e, c) in cases.items()]
    found = table(spark, sf_dir, "lineitem").agg(F.count("*").alias("samples"), *counts)
    rows = F.explode(F.array(*(F.struct(F.lit(name).alias("program"), F.col(name).alias("violations")) for name in cases)))
    return found.select("samples", rows.alias("x")).select("x.program", "samples", "x.violations")


def _suppliers(spark, sf_dir):
    """A frontier of suppliers, with the lines of each as its edges."""
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("node")).agg(F.count("*").alias("deg"))


def wd_blocks_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return blocks(_suppliers(spark, sf_dir), 4).select("worker", "node", "offset", "len")


def ns_split_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return split_map(_suppliers(spark, sf_dir), 64)


def hp_sublists_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ld.sublist_report(_suppliers(spark, sf_dir).withColumn("superstep", F.lit(1).cast("long")), 50, 0)


def hp_tail_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Launches for the suppliers in slices of 5 lines, without and with the switch."""
    front = _suppliers(spark, sf_dir).withColumn("superstep", F.lit(1).cast("long"))
    parts = [ld.sublist_report(front, 5, s).agg(F.count("*").alias("launches")).withColumn("switch_below", F.lit(s).cast("long")) for s in (0, 1024)]
    return parts[0].unionByName(parts[1])


def betweenness(view):
    """Over paths from all nodes to all nodes."""
    return lambda spark, d: extras.betweenness(graph(spark, d, view))


def dependencies(view):
    """The part of betweenness that the paths from the view's source give."""
    return lambda spark, d: extras.dependencies(graph(spark, d, view), source(view))


def rank_time(view):
    """Strategies in order of makespan, of four-byte words and of ease of building: three axes."""

    def run(spark, d):
        spans = balance(view)(spark, d).groupBy("strategy").agg(F.sum("makespan").alias("makespan"))
        ease = spark.createDataFrame(list(ms.COMPLEXITY.items()), "strategy string, ease int")
        order = lambda c: F.rank().over(Window.partitionBy(F.lit(0)).orderBy(c))  # noqa: E731  (five rows)
        rows = spans.join(memory(view)(spark, d).select("strategy", "words"), "strategy").join(ease, "strategy")
        return rows.select("strategy", order("makespan").alias("time_rank"), order("words").alias("memory_rank"), order("ease").alias("ease_rank"))

    return run


def udtf_split_node(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = graph(spark, sf_dir, "part_next")
    tables.register(spark)
    frame = g.degrees().select("node", "deg", F.lit(_mdt(g)).alias("mdt"))
    return spark.sql("SELECT d.node AS parent, s.child_no, s.part_deg FROM {d} d, LATERAL split_node(d.deg, d.mdt) s", d=frame)


def udtf_frontier_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    tables.register(spark)
    return spark.sql("SELECT * FROM frontier_blocks(TABLE(SELECT node, deg FROM {d}) WITH SINGLE PARTITION ORDER BY (node), 4)", d=_suppliers(spark, sf_dir))


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {}
    for v in STATS_VIEWS:
        for name, f in (("graph_stats", stats), ("outdegree_hist", outdegree_hist), ("degree_bins", degree_bins), ("mdt", mdt)):
            out[f"{name}_{v}"] = f(v)
    for v in ("part_next", "supplier_part", "order_part", "event_hub"):
        for name, f in (("mdt_rules", mdt_rules), ("ns_split", ns_split), ("ns_degrees", ns_degrees), ("ns_invariants", ns_invariants), ("csr_pages", csr_pages), ("coo_roundtrip", coo_roundtrip), ("scan", scan_query), ("wd_blocks", wd_blocks), ("memory_words", memory), ("rank_memory", rank_memory)):
            out[f"{name}_{v}"] = f(v)
    for v in ("part_next", "event_hub"):
        for s in ms.STRATEGIES:
            out[f"loads_{s.lower()}_{v}"] = load_query(s, v)
        out[f"balance_{v}"] = balance(v)
        out[f"hp_sublists_{v}"] = hp_sublists(v)
        out[f"hp_noswitch_{v}"] = hp_sublists(v, 0)
        out[f"ep_pushes_{v}"] = ep_pushes(v)
        out[f"bfs_parents_{v}"] = bfs_parents(v)
        out[f"level_sizes_{v}"] = level_sizes(v)
    for v in SEARCH_VIEWS:
        for s in ms.STRATEGIES:
            out[f"bfs_{s.lower()}_{v}"] = search("bfs", s, v)
    for s in ms.STRATEGIES:
        for v in SSSP_VIEWS:
            out[f"sssp_{s.lower()}_{v}"] = search("sssp", s, v)
        out[f"bfs_{s.lower()}_event_lattice"] = search("bfs", s, "event_lattice")
    out["bfs_wd_part_grid"] = search("bfs", "WD", "part_grid")
    out["bfs_ep_token_bigram"], out["sssp_hp_token_bigram"] = search("bfs", "EP", "token_bigram"), search("sssp", "HP", "token_bigram")
    out["bfs_ep_fk_entities"] = search("bfs", "EP", "fk_entities")
    for name, (program, s, v, options) in VARIANTS.items():
        out[name] = variant(program, s, v, **options)
    for v in ("part_next", "event_hub"):
        out[f"ep_chunking_{v}"], out[f"run_metrics_{v}"] = ep_chunking(v), run_metrics(v, "WD")
        out[f"wd_range_join_{v}"] = wd_range_join(v)
    out["loads_per_node_event_hub"] = loads_per_node("event_hub")
    out["load_cv_bs_event_hub"], out["load_cv_wd_event_hub"], out["udaf_gini_load"] = load_spread("BS", "event_hub"), load_spread("WD", "event_hub"), udaf_gini_load
    out["tasks_hold_workers_event_hub"], out["rank_strategies_event_hub"] = tasks_hold_workers("event_hub"), rank_time("event_hub")
    out["bfs_multi_part_next"] = multi_source("part_next")
    out["neighbour_median_part_next"], out["weighted_sum_part_next"] = gathered(programs.NEIGHBOUR_MEDIAN, "part_next"), gathered(programs.WEIGHTED_SUM, "part_next")
    out["spanning_forest_part_next"], out["spanning_forest_part_grid"] = forest("part_next"), forest("part_grid")
    out["components_event_hub"], out["widest_supplier_part"] = components("event_hub"), widest("supplier_part")
    out["strategies_agree_supplier_part"] = agree("supplier_part")
    out["distributive_check"] = distributive_check
    out["betweenness_turn_chain"], out["dependencies_part_next"] = betweenness("turn_chain"), dependencies("part_next")
    out |= {f.__name__: f for f in (udtf_split_node, udtf_frontier_blocks)}
    out |= {f.__name__: f for f in (wd_blocks_example, ns_split_example, hp_sublists_example, hp_tail_example)}
    keys = lambda spark, d, name, key: table(spark, d, name).select(F.col(key).alias("id"))
    out["gen_rmat"] = lambda spark, d: generators.rmat(keys(spark, d, "orders", "o_orderkey"), 8, 42)
    out["gen_er"] = lambda spark, d: generators.erdos_renyi(keys(spark, d, "orders", "o_orderkey"), 256, 42)
    out["gen_lattice"] = lambda spark, d: generators.lattice(keys(spark, d, "events", "event_id"), 512, 42)
    out["knn_embedding_knn"] = lambda spark, d: VIEWS["embedding_knn"](spark, d)
    return out | relational.queries() | batches.queries()
