"""Frontier-driven supersteps to a fixed point."""

from __future__ import annotations

import time
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.measures import parts_of
from ..graph import Graph
from ..operators.programs import BFS, COMPONENTS, SSSP, WIDEST, Program, require_distributive
from ..operators.strategies import PLANS, Front, Options, Work, laid_out, placed, relaxed, threshold
from . import chain
from .lineage import Table, counted

#: Tables of improvements that are kept apart before they are merged into the state.
DELTAS = 12
#: Candidates up to which the state is looked up by them instead of being shuffled, if it has over so many times more nodes.
LOOKUP_ROWS, LOOKUP_SHARE = 200_000, 20
#: Nodes up to which the whole state is written anew each superstep: fewer files than improvements kept apart.
SMALL_NODES = 1 << 18
METRICS = "superstep long, frontier long, improved long, active_edges long, relaxations long, launches long, scan_launches long, pushes long, edge_pushes long, child_pushes long, sublist_pushes long, kernel_s double, overhead_s double"
LOADS = "superstep long, launch long, worker long, task long, load long"


@dataclass
class Run:
    """``state``: ``node``, ``value``, ``step`` (superstep of the last improvement).

    ``rows``: a dict of ``METRICS`` for each superstep, counted while it ran; ``loads``: with ``Options.record``, tables
    ``LOADS`` of the edges that each worker of each launch was given.  Overhead is all but the relaxing jobs: layouts,
    threshold, lists and plans.
    """

    state: DataFrame
    supersteps: int
    strategy: str
    kernel_s: float
    overhead_s: float
    rows: list[dict] = field(default_factory=list)
    loads: list[Table] = field(default_factory=list)
    options: Options = field(default_factory=Options)

    @property
    def frontiers(self) -> list[int]:
        return [r["frontier"] for r in self.rows]

    @property
    def metrics(self) -> DataFrame:
        names = [x.split()[0] for x in METRICS.split(", ")]
        return self.state.sparkSession.createDataFrame([tuple(r[n] for n in names) for r in self.rows], METRICS)

    @property
    def worker_loads(self) -> DataFrame:
        """``superstep``, ``launch`` (from 0), ``worker`` (from 1), ``task``, ``load``, as placed."""
        if not self.loads:
            return self.state.sparkSession.createDataFrame([], LOADS)
        return reduce(DataFrame.unionByName, [x.frame for x in self.loads])


def _sums(mdt: int | None, step: int) -> dict:
    """What is counted of a superstep's improvements while they are written: rows, rows with edges, edges, children of a split, extremes."""
    new = F.col("step") == step
    total = lambda c: F.coalesce(F.sum(F.when(new, c)), F.lit(0))
    children = parts_of(F.col("deg"), mdt) - 1 if mdt else F.lit(0)
    return {"n": F.count_if(new), "busy": F.count_if(new & (F.col("deg") > 0)), "edges": total(F.col("deg")), "children": total(children), "best": F.min(F.when(new, F.col("value"))), "worst": F.max(F.when(new, F.col("value")))}


class _State:
    """Rows ``node``, ``value`` (null: not reached), ``deg``, ``step``: a merged table of all nodes and the improvements since."""

    def __init__(self, first: Table, program: Program, small: bool):
        self.tables, self.program, self.small = [first], program, small

    def frame(self) -> DataFrame:
        """All that is known: of a node's rows the best value counts."""
        first = self.tables[0]
        return first.spark.read.schema(first.schema).parquet(*(t.path for t in self.tables))

    def front(self, step: int) -> DataFrame:
        return self.tables[-1].frame.where((F.col("step") == step) & (F.col("deg") > 0)).select("node", "value", "deg")

    def whole(self) -> DataFrame:
        return self.frame().groupBy("node").agg(self.program.combine(F.col("value")).alias("value"), F.max("deg").alias("deg"), F.max("step").alias("step"))

    def add(self, table: Table) -> None:
        """The improvements, or in small searches all rows anew."""
        if self.small:
            self.tables[0].drop()
            self.tables = [table]
            return
        self.tables.append(table)
        if len(self.tables) > DELTAS:
            rest = self.tables[:-1]
            own, self.tables = self.tables[-1], rest
            merged = Table(self.whole(), "state")
            for t in rest:
                t.drop()
            self.tables = [merged, own]


def _candidates(work: Work, program: Program, opts: Options, step: int, loads: list[Table]) -> tuple[DataFrame, Observation]:
    """``node``, ``cand`` of the edges that the workers relax, where nothing is condensed the best of each worker, and their number."""
    rows = placed(work, opts)
    if opts.record:
        table = Table(rows.withColumn("task", F.spark_partition_id().cast("long")), "placed")
        load = F.sum(F.size("part")) if "part" in rows.columns else F.count("*")
        part = table.frame.groupBy("launch", (F.col("worker") + 1).alias("worker"), "task").agg(load.cast("long").alias("load"))
        loads.append(Table(part.select(F.lit(step).cast("long").alias("superstep"), "launch", "worker", "task", "load"), "loads"))
        rows = placed(Work(table.frame.drop("task"), work.launches, work.workers), opts)
    seen = Observation()
    edges = relaxed(rows, program).observe(seen, F.count("*").alias("relaxations"))
    if opts.condense == "never":
        edges = edges.groupBy("dst", "worker").agg(program.combine(F.col("cand")).alias("cand"))
    return edges.select(F.col("dst").alias("node"), "cand"), seen


def _merged(cands: DataFrame, state: _State, program: Program, opts: Options, step: int, lookup: bool) -> DataFrame:
    """State rows after a superstep: those of all nodes in small searches, else those that improved.

    Candidates and known rows meet in one aggregate by node, candidates combined before they move.  With ``lookup`` the
    candidates are written first and, being few, stand beside the known rows, which then don't move.
    """
    known, never = state.frame(), opts.condense == "never"
    if lookup:
        cands = Table(cands if never else cands.groupBy("node").agg(program.combine(F.col("cand")).alias("cand")), "candidates").frame
        known = known.join(F.broadcast(cands.select("node").distinct()), "node", "left_semi")
    none = lambda kind: F.lit(None).cast(kind)
    rows = cands.select("node", "cand", none("long").alias("old"), none("long").alias("deg"), none("int").alias("step"))
    rows = rows.unionByName(known.select("node", none("long").alias("cand"), F.col("value").alias("old"), "deg", "step"))
    each = F.collect_list("cand") if never else program.combine(F.col("cand"))  # at most a value for each worker
    met = rows.groupBy("node").agg(each.alias("cand"), program.combine(F.col("old")).alias("old"), F.max("deg").alias("deg"), F.max("step").alias("step"))
    if never:
        met = met.select("node", F.explode("cand").alias("cand"), "old", "deg", "step")
    won = F.col("cand").isNotNull() & (F.col("old").isNull() | program.better(F.col("cand"), F.col("old")))
    if not state.small:
        return met.where(won).select("node", F.col("cand").alias("value"), "deg", F.lit(step).alias("step"))
    return met.select("node", F.when(won, F.col("cand")).otherwise(F.col("old")).alias("value"), "deg", F.when(won, F.lit(step)).otherwise(F.col("step")).alias("step"))


def traverse(graph: Graph, program: Program, seeds: DataFrame, strategy: str = "WD", options: Options | None = None, max_supersteps: int | None = None, target=None, data_driven: bool = True, resume: DataFrame | None = None) -> Run:
    """Run ``program`` from ``seeds`` (``node``, ``value``) until no value improves.

    A superstep hands the frontier's edges to workers by the strategy's plan, keeps each destination's best candidate
    (combined within the workers before the shuffle) and writes the candidates that improve on the state: they are the
    next frontier, and only they are written.  Improvements are merged into the state every ``DELTAS`` supersteps.
    Values are read as they stood when the superstep began.  ``target`` ends a search once no frontier value is better
    than that node's (edges must not make values better); ``data_driven=False`` relaxes from all reached nodes; ``resume`` (``node``, ``value``): values
    known from before, of which only better ones are handed on.  Once a search counts as long (``chain.begins``) its
    supersteps of few edges run one after the other in one job.
    """
    require_distributive(program, strategy)
    if program.aggregate:
        raise ValueError(f"{program.name} has no better value: use gather")
    options, began = options or Options(), time.time()
    own = graph.cached()
    mdt = threshold(own, options) if strategy in ("NS", "HP") else None
    laid_out(strategy, own, options)
    known = seeds.select("node", F.col("value").cast("long").alias("value"), F.lit(0).alias("step"))
    if resume is not None:
        known = known.unionByName(resume.select("node", F.col("value").cast("long").alias("value"), F.lit(-1).alias("step")))
    start = known.groupBy("node").agg(program.combine(F.col("value")).alias("value"), F.max("step").alias("step"))
    first = own.all_degrees().join(start.withColumnRenamed("node", "_node"), F.col("node") == F.col("_node"), "full")
    first = first.select("node", "value", "deg", "step")
    table, seen = counted(first, "state", **_sums(mdt, 0), nodes=F.count("*"), all_edges=F.coalesce(F.sum("deg"), F.lit(0)), unknown=F.count_if(F.col("node").isNull()))
    if seen["unknown"]:
        raise ValueError("a source is no node of the graph")
    n_nodes, all_edges = seen["nodes"], seen["all_edges"]
    state = _State(table, program, n_nodes <= SMALL_NODES and options.condense != "never")
    long_paths = chain.fits(program, options, data_driven, target, n_nodes + all_edges, graph.edges.schema["src"].dataType.simpleString())
    overhead, kernel, k = time.time() - began, 0.0, 0
    rows: list[dict] = []
    loads: list[Table] = []
    while seen["busy"] and (max_supersteps is None or k < max_supersteps):
        if long_paths and chain.begins(k, seen["edges"], sum(r["active_edges"] for r in rows), all_edges):
            began = time.time()
            made = Table(chain.chained(own.edges, state.whole(), program, strategy, options, mdt, k, max_supersteps, state.small), "chain")
            steps = [r.asDict() for r in made.frame.where("superstep is not null").select(*(c.split()[0] for c in chain.COUNTS.split(", "))).orderBy("superstep").collect()]
            table, seen = counted(made.frame.where("superstep is null").select("node", "value", "deg", "step"), "state", **_sums(mdt, k + len(steps)))
            made.drop()
            k, spent = k + len(steps), time.time() - began
            kernel += spent
            for r in steps:
                r |= {"relaxations": r["active_edges"], "pushes": r["improved"] + r["child_pushes"], "edge_pushes": 0, "kernel_s": spent / len(steps), "overhead_s": 0.0}
            rows += steps
            state.add(table)
            continue
        began, k = time.time(), k + 1
        now = state.front(k - 1)
        if not data_driven:
            now = state.whole().where("value is not null and deg > 0").select("node", "value", "deg")
            seen = now.agg(F.count("*").alias("busy"), F.sum("deg").alias("edges")).first()
        front = Front(now, seen["busy"], seen["edges"])
        work = PLANS[strategy](front, own, program, options)
        planned = time.time()
        cands, relaxed_n = _launched(work, program, options, k, loads)
        table, found = counted(_merged(cands, state, program, options, k, front.edges <= LOOKUP_ROWS < n_nodes // LOOKUP_SHARE), "state", **_sums(mdt, k))
        spent = time.time() - planned
        overhead, kernel = overhead + planned - began, kernel + spent
        pushed = {"edge_pushes": found["edges"] if strategy == "EP" and not options.chunked else 0, "child_pushes": found["children"] if strategy == "NS" else 0}
        rows.append({
            "superstep": k, "frontier": front.nodes, "improved": found["n"], "active_edges": front.edges, "relaxations": relaxed_n(), "launches": work.launches, "scan_launches": work.counts.get("scan_launches", 0),
            "pushes": found["edges"] if strategy == "EP" and not options.chunked else found["n"] + pushed["child_pushes"], **pushed, "sublist_pushes": work.counts.get("sublist_pushes", 0), "kernel_s": spent, "overhead_s": planned - began,
        })
        seen = found
        if found["n"]:
            state.add(table)
        elif not data_driven:
            break
        if target is not None and found["n"]:
            settled = state.frame().where(F.col("node") == F.lit(target)).agg(program.combine(F.col("value"))).first()[0]
            if settled is not None and (found["best"] >= settled if program.least else found["worst"] <= settled):
                break
    began = time.time()
    final = Table(state.whole().where("value is not null").select("node", "value", "step"), "result")
    for t in state.tables:
        t.drop()
    own.release()
    return Run(final.frame, k, strategy, kernel, overhead + time.time() - began, rows, loads, options)


def _launched(work: Work, program: Program, opts: Options, step: int, loads: list[Table]):
    """Candidates of all launches: in one job, or launch by launch with a written table each."""
    if opts.fused or work.launches == 1:
        best, seen = _candidates(work, program, opts, step, loads)
        return best, lambda: seen.get["relaxations"]
    parts, total = [], 0
    for launch in range(work.launches):
        own = Work(work.rows.where(F.col("launch") == launch), 1, work.workers, work.counts)
        best, seen = _candidates(own, program, opts, step, loads)
        parts.append(Table(best.groupBy("node").agg(program.combine(F.col("cand")).alias("cand")), "launch").frame)
        total += seen.get["relaxations"]
    return reduce(DataFrame.unionByName, parts), lambda: total


def seeds_of(graph: Graph, sources: list) -> DataFrame:
    kind = graph.edges.schema["src"].dataType.simpleString()
    return graph.edges.sparkSession.createDataFrame([(s, 0) for s in sources], f"node {kind}, value long")


def bfs(graph: Graph, sources: list, strategy: str = "WD", **more) -> Run:
    return traverse(graph, BFS, seeds_of(graph, sources), strategy, **more)


def sssp(graph: Graph, sources: list, strategy: str = "WD", **more) -> Run:
    return traverse(graph, SSSP, seeds_of(graph, sources), strategy, **more)


def components(graph: Graph, strategy: str = "WD", **more) -> Run:
    """Least id reachable forwards; over both directions of each edge, the connected components.  Ids must be long."""
    return traverse(graph, COMPONENTS, graph.nodes().select("node", F.col("node").alias("value")), strategy, **more)


def widest(graph: Graph, sources: list, strategy: str = "WD", **more) -> Run:
    """Greatest bottleneck weight on a path from the sources."""
    return traverse(graph, WIDEST, seeds_of(graph, sources).select("node", F.lit((1 << 62)).alias("value")), strategy, **more)


def gather(graph: Graph, program: Program, values: DataFrame, strategy: str = "BS", rounds: int = 1) -> DataFrame:
    """``node``, ``value`` after rounds in which every node that edges lead to takes the aggregate of what they carry; others keep theirs.

    A program that is not distributive gathers whole nodes (BS); others sum up parts first.
    """
    require_distributive(program, strategy)
    state = values.select("node", "value")
    for _ in range(rounds):
        sent = graph.edges.join(state.withColumnRenamed("node", "src"), "src").select("dst", program.extend(F.col("value"), F.col("w")).alias("cand"))
        new = sent.groupBy(F.col("dst").alias("node")).agg(program.combine(F.col("cand")).alias("new"))
        state = Table(state.join(new, "node", "left").select("node", F.coalesce("new", "value").alias("value")), "round").frame
    return state


def with_parents(graph: Graph, state: DataFrame, program: Program = BFS) -> DataFrame:
    """``node``, ``value``, ``parent``: the least predecessor that gives a node its value; none at sources."""
    edges = graph.edges.join(state.select(F.col("node").alias("src"), F.col("value").alias("from")), "src")
    reached = edges.select(F.col("dst").alias("node"), "src", program.extend(F.col("from"), F.col("w")).alias("value"))
    parents = reached.join(state.select("node", "value"), ["node", "value"]).groupBy("node").agg(F.min("src").alias("parent"))
    return state.select("node", "value", "step").join(parents, "node", "left").select("node", "value", F.when(F.col("step") > 0, F.col("parent")).alias("parent"))
