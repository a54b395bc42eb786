"""Five ways of dividing a superstep's edges among workers, each as a plan from the frontier to placed work.

BS whole nodes; EP single edges; WD equal blocks of the frontier's edges; NS nodes split beforehand; HP slices of at most
MDT edges a node, launch after launch, with a switch to blocks for short lists.

A plan gives every piece of work a launch and a worker.  Pieces meet their pages by (node, page), so a hub's edges lie in
many tasks when they are read, and are then sent to the partition of their launch and worker: what a strategy decides is
what a task gets.  Pages know their first edge by arithmetic, so no plan searches.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.measures import BINS, find_mdt, parts_of
from ..graph import Graph
from . import scan
from .programs import Program

#: Launches that get partitions of their own; further ones share them.
LAUNCHES = 32
#: Partitions for workers of one node each.
NODE_TASKS = 256
#: Entries up to which EP's worklist may be broadcast to the edge list.
PUSHED_ROWS = 100_000


@dataclass
class Options:
    """``workers``: a number, or ``per_node`` (BS only: a worker for each frontier node).

    ``assign``: round_robin or hash (BS).  ``chunked``: whether EP pushes a node's edges in one go.  ``condense``:
    per_superstep, or never, where each worker's improvement of a node is a worklist entry of its own.  ``fused``: HP's
    launches as rows of one job, else a job each.  ``depth``: 2 cuts HP's sublists into groups of ``group`` nodes.
    ``place``: workers, or pages to leave edges where they lie and only account for the division.  ``record``: keep
    the loads of the workers as they were placed.
    """

    workers: int | str = 8
    mdt: str | int = "auto"
    bins: int = BINS
    switch_below: int = 1024
    assign: str = "round_robin"
    chunked: bool = True
    condense: str = "per_superstep"
    fused: bool = True
    depth: int = 1
    group: int = 1024
    place: str = "workers"
    record: bool = False
    notes: dict = field(default_factory=dict)


@dataclass
class Work:
    """A superstep's placed work: ``rows`` hold ``launch``, ``worker`` (from 0), ``value`` and ``part`` (an array of edges) or ``dst``, ``w``.

    ``counts``: launches, and entries pushed or mirrored for them, by name.
    """

    rows: DataFrame
    launches: int
    workers: int
    counts: dict[str, int] = field(default_factory=dict)


@dataclass(frozen=True)
class Front:
    """A frontier ``node``, ``value``, ``deg`` (over 0) with what was counted while it was written."""

    rows: DataFrame
    nodes: int
    edges: int


_LONG = "long"


#: Keys by which a layout's pages are bucketed.
PLACE = ["node", "page"]


def laid_out(strategy: str, graph: Graph, opts: Options) -> DataFrame:
    """The layout that a strategy reads: the edge list, the rows of the split graph, or the rows; written once."""
    if strategy == "EP":
        return graph.kept("flat", graph.flat, PLACE) if opts.chunked else graph.kept("flat-single", graph.flat, [*PLACE, "at"])
    if strategy == "NS":
        mdt = threshold(graph, opts)
        return graph.kept(f"split-{mdt}", lambda: split_pages(graph, mdt), ["node", "child_no", "page"])
    return graph.kept("pages", graph.pages, PLACE)


def _long(x) -> Column:
    return F.lit(x).cast(_LONG)


def _share(edges: int, workers: int) -> int:
    return max(1, -(-int(edges) // workers))


def _on_pages(ranges: DataFrame, graph: Graph) -> DataFrame:
    """Ranges (``start``, ``len``) of nodes' edges cut at page borders: ``page``, ``at`` (in the page), ``len``."""
    size = graph.page
    page = F.explode(F.sequence(F.floor(F.col("start") / size), F.floor((F.col("start") + F.col("len") - 1) / size)))
    cut = ranges.select("*", page.alias("page"))
    lo = F.greatest(F.col("start"), F.col("page") * size)
    hi = F.least(F.col("start") + F.col("len"), (F.col("page") + 1) * size)
    return cut.select("launch", "worker", "node", "value", "page", (lo - F.col("page") * size).alias("at"), (hi - lo).alias("len"))


def _slices(ranges: DataFrame, graph: Graph) -> DataFrame:
    """The edges of ranges as arrays."""
    pages = laid_out("WD", graph, Options()).select("node", "page", "adj")
    met = _on_pages(ranges, graph).join(pages, ["node", "page"])
    return met.select("launch", "worker", "value", F.slice("adj", (F.col("at") + 1).cast("int"), F.col("len").cast("int")).alias("part"))


def by_node(front: Front, graph: Graph, program: Program, opts: Options) -> Work:
    """BS: worker ``rank % workers`` takes all edges of a frontier node."""
    if opts.assign == "hash" and opts.workers != "per_node":
        ranked, workers = front.rows.withColumn("worker", F.pmod(F.xxhash64("node"), _long(opts.workers))), int(opts.workers)
    else:
        workers = max(1, front.nodes) if opts.workers == "per_node" else int(opts.workers)
        ranked = scan.inclusive(front.rows, ["node"], "deg", rows=front.nodes).withColumn("worker", F.col("rank") % workers)
    ranges = ranked.select(_long(0).alias("launch"), "worker", "node", "value", _long(0).alias("start"), F.col("deg").alias("len"))
    return Work(_slices(ranges, graph), 1, workers, {"node_pushes": front.nodes})


def by_edge(front: Front, graph: Graph, program: Program, opts: Options) -> Work:
    """EP: the frontier's edges, numbered on, go to the workers one after the other.

    ``chunked``: a node's edges enter the worklist as one entry and are spread where the edge list lies; otherwise every
    edge is an entry of its own before it meets the edge list, which then lies by edge; single entries are never broadcast,
    others only if they are few by count, for the size that Spark knows is that of the compressed files of the frontier.
    """
    lo = F.col("hi") - F.col("deg")
    rows = scan.inclusive(front.rows, ["node"], "deg", rows=front.nodes).select("node", "value", "deg", lo.alias("lo"))
    pages = rows.withColumn("page", F.explode(F.sequence(_long(0), F.floor((F.col("deg") - 1) / graph.page).cast(_LONG)))).withColumn("lo", F.col("lo") + F.col("page") * graph.page)
    flat = laid_out("EP", graph, opts)
    flat = flat if program.weighted else flat.drop("w")
    if opts.chunked:
        pushed = pages.select("node", "page", "value", "lo")
        few = front.nodes + front.edges // graph.page <= PUSHED_ROWS
        met = (pushed if few else pushed.hint("merge")).join(flat, ["node", "page"])
    else:
        held = F.least(_long(graph.page), F.col("deg") - F.col("page") * graph.page)
        single = pages.withColumn("at", F.explode(F.sequence(F.lit(0), (held - 1).cast("int")))).select("node", "page", "at", "value", "lo")
        met = single.hint("merge").join(flat, ["node", "page", "at"])
    w = F.col("w") if program.weighted else F.lit(1)
    out = met.select(_long(0).alias("launch"), ((F.col("lo") + F.col("at")) % int(opts.workers)).alias("worker"), "value", "dst", w.alias("w"))
    return Work(out, 1, int(opts.workers), {"node_pushes" if opts.chunked else "edge_pushes": front.nodes if opts.chunked else front.edges})


def blocks(frontier: DataFrame, workers: int, base: str | None = None, rows: int | None = None, edges: int | None = None, range_join: bool = False) -> DataFrame:
    """``worker`` (from 1), ``node``, ``offset`` (edges of the node before the piece), ``len`` and the frontier's other columns.

    ``frontier``: ``node``, ``deg``; ``base``: column of edges already handled; ``rows``, ``edges``: its size where known.
    Worker t takes edges (t-1)q .. tq of the concatenated lists with q the rounded-up share; a node gives one piece for
    each worker that its edges touch, found from its own running total.  ``range_join`` finds them by meeting the
    workers' ranges instead, a cross-check.
    """
    left = F.col("deg") - F.col(base) if base else F.col("deg")
    summed = scan.inclusive(frontier.select("*", left.alias("_left")).where("_left > 0"), ["node"], "_left", rows=rows)
    if edges is None:
        edges = summed.agg(F.max("hi")).first()[0] or 0
    share = _share(edges, workers)
    lo = F.col("hi") - F.col("_left")
    if range_join:
        every = frontier.sparkSession.range(workers).select(F.col("id").alias("_t"))
        pieces = summed.join(F.broadcast(every), (F.col("_t") * share < F.col("hi")) & ((F.col("_t") + 1) * share > lo))  # a row for each worker
    else:
        pieces = summed.select("*", F.explode(F.sequence(F.floor(lo / share), F.floor((F.col("hi") - 1) / share))).alias("_t"))
    start, end = F.greatest(lo, F.col("_t") * share), F.least(F.col("hi"), (F.col("_t") + 1) * share)
    done = F.col(base) if base else F.lit(0)
    return pieces.select(*frontier.columns, (F.col("_t") + 1).alias("worker"), (start - lo + done).alias("offset"), (end - start).alias("len"))


def _block_ranges(rows: DataFrame, workers: int, launch: int, nodes: int, edges: int, base: str | None = None) -> DataFrame:
    cut = blocks(rows, workers, base, nodes, edges)
    return cut.select(_long(launch).alias("launch"), (F.col("worker") - 1).alias("worker"), "node", "value", F.col("offset").alias("start"), "len")


def by_block(front: Front, graph: Graph, program: Program, opts: Options) -> Work:
    """WD: the frontier's edges in equal blocks; a node may straddle workers."""
    ranges = _block_ranges(front.rows, int(opts.workers), 0, front.nodes, front.edges)
    return Work(_slices(ranges, graph), 1, int(opts.workers), {"node_pushes": front.nodes, "scan_launches": 2})


def threshold(graph: Graph, opts: Options) -> int:
    if "mdt" not in opts.notes:
        opts.notes["mdt"] = find_mdt(graph.all_degrees(), opts.mdt, opts.bins)
    return opts.notes["mdt"]


def _bound(child: Column, deg: Column, parts: Column) -> Column:
    """The first edge of a part: the least position p with floor(p * parts / deg) = child."""
    return F.ceil(child * deg / parts).cast(_LONG)


def split_edges(graph: Graph, mdt: int) -> DataFrame:
    """``parent``, ``child_no``, ``parts``, ``at`` (in the part), ``dst``, ``w``: each node's edges dealt evenly over its parts; in-edges stay with the parent."""
    rows = graph.pages().select("node", "deg", "first", F.posexplode("adj").alias("at", "e"))
    deg, place = F.col("deg"), F.col("first") + F.col("at")
    rows = rows.withColumn("parts", parts_of(deg, mdt)).withColumn("child_no", F.floor(place * F.col("parts") / deg).cast(_LONG))
    return rows.select(F.col("node").alias("parent"), "child_no", "parts", (place - _bound(F.col("child_no"), deg, F.col("parts"))).alias("at"), "e.dst", "e.w")


def split_map(degrees: DataFrame, mdt: int) -> DataFrame:
    """``parent``, ``child_no``, ``part_deg`` of every part of the nodes over ``mdt``; the parent itself is part 0."""
    over = degrees.where(F.col("deg") > mdt).withColumnRenamed("node", "parent")
    return _mirrored(over, mdt).select("parent", "child_no", "part_deg")


def _mirrored(rows: DataFrame, mdt: int) -> DataFrame:
    """A row for each part of a node: ``child_no``, ``part_deg`` beside the row's columns."""
    parts, child = F.col("parts"), F.col("child_no")
    rows = rows.withColumn("parts", parts_of(F.col("deg"), mdt)).withColumn("child_no", F.explode(F.sequence(_long(0), F.col("parts") - 1)))
    return rows.withColumn("part_deg", _bound(child + 1, F.col("deg"), parts) - _bound(child, F.col("deg"), parts))


def split_pages(graph: Graph, mdt: int) -> DataFrame:
    """The graph after splitting, paged: ``node``, ``child_no``, ``page`` (within the part), ``adj``."""
    at = F.sort_array(F.collect_list(F.struct("at", "dst", "w")))
    rows = split_edges(graph, mdt).withColumn("page", F.floor(F.col("at") / graph.page).cast(_LONG))
    return rows.groupBy(F.col("parent").alias("node"), "child_no", "page").agg(F.transform(at, lambda x: F.struct(x["dst"].alias("dst"), x["w"].alias("w"))).alias("adj"))


def by_split(front: Front, graph: Graph, program: Program, opts: Options) -> Work:
    """NS: the graph was split beforehand; an improved parent mirrors its value to its children, then whole parts are dealt out as in BS."""
    mdt, workers = threshold(graph, opts), int(opts.workers)
    split = laid_out("NS", graph, opts)
    most = front.nodes + front.edges // max(1, mdt)
    ranked = scan.inclusive(_mirrored(front.rows, mdt), ["node", "child_no"], "part_deg", rows=most)
    pages = F.explode(F.sequence(_long(0), F.floor((F.col("part_deg") - 1) / graph.page).cast(_LONG)))
    met = ranked.withColumn("page", pages).withColumn("worker", F.col("rank") % workers).join(split, ["node", "child_no", "page"])
    return Work(met.select(_long(0).alias("launch"), "worker", "value", F.col("adj").alias("part")), 1, workers, {"node_pushes": front.nodes})


def sublists(sizes: DataFrame, mdt: int, switch_below: int) -> tuple[list[int], int | None]:
    """The sublists' sizes before the switch, and the launch at which blocks take over (None: never), from a histogram ``deg``, ``n``."""
    steps = sizes.select(F.ceil(F.col("deg") / mdt).cast(_LONG).alias("k"), "n").groupBy("k").agg(F.sum("n").alias("n")).orderBy("k").collect()  # a row for each number of launches
    ends = {r["k"]: r["n"] for r in steps}
    left, out = sum(ends.values()), []
    for s in range(max(ends, default=0)):
        left -= ends.get(s, 0)
        if left < switch_below:
            return out, s
        out.append(left)
    return out, None


def by_slices(front: Front, graph: Graph, program: Program, opts: Options) -> Work:
    """HP: slices of at most MDT edges of every unfinished node; blocks for what is left once few nodes are unfinished.

    With ``depth`` 2 a sublist is cut further, into launches of at most ``group`` nodes.
    """
    mdt, workers = threshold(graph, opts), int(opts.workers)
    if front.nodes < opts.switch_below:
        return Work(_slices(_block_ranges(front.rows, workers, 0, front.nodes, front.edges), graph), 1, workers, {"node_pushes": front.nodes, "scan_launches": 2})
    sizes, switch = sublists(front.rows.groupBy("deg").agg(F.count("*").alias("n")), mdt, opts.switch_below)
    cuts = [-(-n // opts.group) if opts.depth > 1 else 1 for n in sizes]
    parts = []
    if sizes:
        mine = F.least(F.ceil(F.col("deg") / mdt), F.lit(len(sizes))).cast(_LONG)
        sliced = front.rows.withColumn("s", F.explode(F.sequence(_long(0), mine - 1)))
        sliced = scan.inclusive(sliced, ["node"], "deg", ["s"], rows=sum(sizes))
        group = F.floor(F.col("rank") / opts.group).cast(_LONG) if opts.depth > 1 else _long(0)
        within = F.col("rank") % opts.group if opts.depth > 1 else F.col("rank")
        firsts = F.array(*(_long(sum(cuts[:s])) for s in range(len(cuts)))) if opts.depth > 1 else None
        launch = (F.element_at(firsts, (F.col("s") + 1).cast("int")) + group) if opts.depth > 1 else F.col("s")
        start = F.col("s") * mdt
        parts.append(sliced.select(launch.alias("launch"), (within % workers).alias("worker"), "node", "value", start.alias("start"), F.least(_long(mdt), F.col("deg") - start).alias("len")))
    launches = sum(cuts)
    if switch is not None:
        tail = front.rows.where(F.col("deg") > switch * mdt).withColumn("done", _long(switch * mdt))
        held = tail.agg(F.count("*"), F.coalesce(F.sum(F.col("deg") - F.col("done")), F.lit(0))).first() if sizes else (front.nodes, front.edges)
        parts.append(_block_ranges(tail, workers, launches, held[0], held[1], "done"))
        launches += 1
    ranges = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    return Work(_slices(ranges, graph), launches, workers, {"node_pushes": front.nodes, "sublist_pushes": sum(sizes), "scan_launches": 2 * (switch is not None)})


def placed(work: Work, opts: Options) -> DataFrame:
    """The work in the partitions of its launches and workers."""
    if opts.place != "workers":
        return work.rows
    tasks = min(work.workers, NODE_TASKS) if opts.workers == "per_node" else work.workers
    at = F.col("launch") % min(work.launches, LAUNCHES) * tasks + F.col("worker") % tasks
    return work.rows.repartitionById(tasks * min(work.launches, LAUNCHES), at.cast("int"))


def relaxed(rows: DataFrame, program: Program) -> DataFrame:
    """``worker``, ``dst``, ``cand`` of every edge of placed work."""
    if "part" in rows.columns:
        rows = rows.select("launch", "worker", "value", F.explode("part").alias("e")).select("launch", "worker", "value", "e.dst", "e.w")
    return rows.select("launch", "worker", "dst", program.extend(F.col("value"), F.col("w")).alias("cand"))


PLANS: dict[str, Callable[[Front, Graph, Program, Options], Work]] = {"BS": by_node, "EP": by_edge, "WD": by_block, "NS": by_split, "HP": by_slices}
