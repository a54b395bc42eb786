"""Minimum-cost role repair of conversations over a legal-turn automaton (operator 10).

States are the start and the last turn's role: a system turn may only open, user and assistant turns
alternate, and the first of them is the user's.  Each turn is kept, merged into the last turn of the same
role, relabelled, or preceded by an empty turn; costs add up and the cheapest path over the automaton is
found by dynamic programming.  Then each turn gives the fragment of text that renders it.

A conversation is cut into segments of bounded size at places that its turns fix.  Most are one segment.
For longer ones each segment gives the cheapest cost between every two states; these small matrices are
chained to find where the whole path enters and leaves each segment, and every segment then repairs
itself on its own.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Shared

ROLES = ("system", "user", "assistant")
START = 0
STATES = 4
#: From each state (start, system, user, assistant) the states that may follow.
LEGAL = {0: (1, 2), 1: (2,), 2: (3,), 3: (2,)}
#: Turns of a conversation that stay one segment; of longer ones, numbers of turns that make up a segment.
WHOLE, SPAN = 4096, 256


@dataclass(frozen=True)
class Costs:
    merge: int = 1
    relabel: int = 2
    relabel_unknown: int = 1
    insert: int = 3


def steps(state: int, role: str | None, costs: Costs) -> list[tuple[int, int, str, int]]:
    """(cost, next state, action, inserted state or 0) of the ways to take a turn, best first for equal costs."""
    own = ROLES.index(role) + 1 if role in ROLES else 0
    out = []
    if own:
        if own in LEGAL[state]:
            out.append((0, own, "keep", 0))
        if own == state:
            out.append((costs.merge, own, "merge", 0))
    for to in LEGAL[state]:
        if to != own:
            out.append((costs.relabel if own else costs.relabel_unknown, to, "relabel", 0))
    if own:
        out += [(costs.insert, own, "insert", between) for between in LEGAL[state] if own in LEGAL[between]]
    return out


class Repair:
    """The automaton with its steps tabulated."""

    def __init__(self, costs: Costs):
        self.by_role = {role: [steps(s, role, costs) for s in range(STATES)] for role in (*ROLES, None)}

    def forward(self, roles: list[str | None], entry: int) -> list[list[tuple[int, int, str, int] | None]]:
        """For each turn and state: (cost so far, state before, action, inserted state) of the cheapest way there."""
        costs: list[int | None] = [None] * STATES
        costs[entry] = 0
        out = []
        for role in roles:
            table = self.by_role.get(role, self.by_role[None])
            best: list[tuple[int, int, str, int] | None] = [None] * STATES
            for before, so_far in enumerate(costs):
                if so_far is not None:
                    for cost, to, action, between in table[before]:
                        if best[to] is None or so_far + cost < best[to][0]:
                            best[to] = (so_far + cost, before, action, between)
            costs = [x and x[0] for x in best]
            out.append(best)
        return out

    @staticmethod
    def path(table: list[list[tuple[int, int, str, int] | None]], leave: int) -> list[tuple[int, str, int]]:
        """(state, action, inserted state) of each turn on the way to ``leave``."""
        out, state = [], leave
        for best in reversed(table):
            _, before, action, between = best[state]  # type: ignore[misc]
            out.append((state, action, between))
            state = before
        return out[::-1]

    def matrix(self, roles: list[str | None]) -> list[int]:
        """Cost, then turns begun, between every two states; -1 where there is no way."""
        cost, begun = [], []
        for entry in range(STATES):
            table = self.forward(roles, entry)
            for leave in range(STATES):
                found = table[-1][leave]
                cost.append(found[0] if found else -1)
                begun.append(sum((a != "merge") + (b > 0) for _, a, b in self.path(table, leave)) if found else -1)
        return cost + begun


def chain(matrices: list[list[int]]) -> list[tuple[int, int, int]]:
    """Entry state, exit state and turns begun before, for each segment of the cheapest path from the start."""
    n = STATES * STATES
    costs: list[int | None] = [0, None, None, None]
    came = []
    for m in matrices:
        best: list[tuple[int, int] | None] = [None] * STATES
        for entry, so_far in enumerate(costs):
            if so_far is not None:
                for leave in range(STATES):
                    if (c := m[entry * STATES + leave]) >= 0 and (best[leave] is None or so_far + c < best[leave][0]):
                        best[leave] = (so_far + c, entry)
        costs = [x and x[0] for x in best]
        came.append(best)
    leave = min((s for s in range(STATES) if costs[s] is not None), key=lambda s: costs[s])
    ways = []
    for best in reversed(came):
        entry = best[leave][1]
        ways.append((entry, leave))
        leave = entry
    out, begun = [], 0
    for (entry, leave), m in zip(reversed(ways), matrices, strict=True):
        out.append((entry, leave, begun))
        begun += m[n + entry * STATES + leave]
    return out


_SEGMENT = ["conv_id", "chunk", "turn_of", "part"]


def segments(turns: DataFrame) -> DataFrame:
    """Rows ``conv_id``, ``chunk``, ``turn_of``, ``part``, ``long``, ``turns``: a segment's turns in order.

    Order: turn (null first), then a digest of role and text, role, text.
    """
    rows = turns.select("conv_id", "turn", F.xxhash64("role", "text").alias("tie"), "role", "text")
    chunk = F.floor(F.col("turn") / SPAN).cast("long")
    sizes = rows.groupBy("conv_id", chunk.alias("chunk"), "turn").agg(F.count("*").alias("n"))
    total = sizes.groupBy("conv_id").agg(F.sum("n").alias("total")).where(F.col("total") > WHOLE)
    none = F.lit(None).cast("long")
    if total.isEmpty():
        keyed = rows.select("conv_id", none.alias("chunk"), none.alias("turn_of"), none.alias("part"), F.lit(False).alias("long"), "turn", "tie", "role", "text")
    else:
        total = total.select(F.col("conv_id").alias("_conv"), F.lit(True).alias("long"))
        dense = sizes.groupBy("conv_id", "chunk").agg(F.sum("n").alias("n")).where(F.col("n") > WHOLE).select(F.col("conv_id").alias("_c"), F.col("chunk").alias("_k"), F.lit(True).alias("dense"))
        many = sizes.where(F.col("n") > WHOLE).select(F.col("conv_id").alias("_m"), F.col("turn").alias("_t"), F.ceil(F.col("n") / (WHOLE // 2)).alias("parts"))
        keyed = rows.withColumn("chunk", chunk).join(total, F.col("conv_id").eqNullSafe(F.col("_conv")), "left")
        keyed = keyed.join(dense, F.col("conv_id").eqNullSafe(F.col("_c")) & F.col("chunk").eqNullSafe(F.col("_k")), "left")
        keyed = keyed.join(many, F.col("conv_id").eqNullSafe(F.col("_m")) & F.col("turn").eqNullSafe(F.col("_t")), "left")
        share = F.floor((F.col("tie").cast("double") / (2.0**64) + 0.5) * F.col("parts")).cast("long")
        keyed = keyed.select(
            "conv_id", F.when(F.col("long"), F.col("chunk")).alias("chunk"), F.when(F.col("dense"), F.col("turn")).alias("turn_of"), F.when(F.col("dense"), share).alias("part"), F.coalesce("long", F.lit(False)).alias("long"), "turn", "tie", "role", "text"
        )
    return keyed.groupBy(*_SEGMENT, "long").agg(F.sort_array(F.collect_list(F.struct("turn", "tie", "role", "text"))).alias("turns"))


FRAGMENTS = "conv_id long, position long, turn long, role string, action string, text string, rendered string"


def _open(role: str, first: bool) -> str:
    return ("" if first else "<|end|>\n") + f"<|{role}|>\n"


def repair(turns: DataFrame, costs: Costs = Costs()) -> DataFrame:  # noqa: B008
    """A row for each turn and each empty turn put in: ``conv_id``, ``position`` (repaired turn it belongs to, from 0),
    ``turn`` (null if put in), ``role``, ``action`` (keep, merge, relabel, insert), ``text``, ``rendered``.

    A conversation's rendering is its ``rendered`` in the order of position and turn, then ``<|end|>``.  Roles are
    taken without case and outer blanks; null and unknown roles must be relabelled.  Null texts are empty, rows
    without ``conv_id`` are one conversation, repeated rows are turns of their own.
    """
    machine = Repair(costs)
    own = turns.select(F.col("conv_id").cast("long"), F.col("turn").cast("long"), F.lower(F.trim("role")).alias("role"), "text")
    table = Shared(segments(own), "segments")

    def matrices(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [machine.matrix([t["role"] for t in x]) for x in batch.column("turns").to_pylist()]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in _SEGMENT), pa.array(found, pa.list_(pa.int64()))], [*_SEGMENT, "matrix"])

    def chained(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda x: [-(1 << 63) if x[c] is None else x[c] for c in _SEGMENT])
        found = chain([x["matrix"] for x in rows])
        cols = [[x[c] for x in rows] for c in _SEGMENT] + [[x[i] for x in found] for i in range(3)]
        return pa.Table.from_arrays([pa.array(c, pa.int64()) for c in cols], names=[*_SEGMENT, "entry", "leave", "begun"])

    keys = ", ".join(f"{c} long" for c in _SEGMENT)
    long = table.frame.where("long").drop("long").mapInArrow(matrices, f"{keys}, matrix array<long>")
    ways = long.groupBy("conv_id").applyInArrow(chained, f"{keys}, entry long, leave long, begun long")
    ways = ways.withColumnsRenamed({c: f"_{c}" for c in _SEGMENT})
    met = F.lit(True)
    for c in _SEGMENT:
        met = met & F.col(c).eqNullSafe(F.col(f"_{c}"))

    def emit(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = [x.split()[0] for x in FRAGMENTS.split(", ")]
        for batch in batches:
            rows: list[tuple] = []
            for x in batch.to_pylist():
                roles = [t["role"] for t in x["turns"]]
                table = machine.forward(roles, x["entry"] or START)
                leave = x["leave"]
                if leave is None:
                    leave = min((s for s in range(STATES) if table[-1][s]), key=lambda s: table[-1][s][0])
                at = (x["begun"] or 0) - 1
                for t, (state, action, between) in zip(x["turns"], Repair.path(table, leave), strict=True):
                    if between:
                        at += 1
                        rows.append((x["conv_id"], at, None, ROLES[between - 1], "insert", "", _open(ROLES[between - 1], at == 0)))
                    at += action != "merge"
                    role, text = ROLES[state - 1], t["text"] or ""
                    shown = "\n\n" + text if action == "merge" else _open(role, at == 0) + text
                    rows.append((x["conv_id"], at, t["turn"], role, "keep" if action == "insert" else action, text, shown))
            kinds = [pa.int64()] * 3 + [pa.string()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names)

    short = table.frame.where("not long").select("conv_id", "turns", *(F.lit(None).cast("long").alias(c) for c in ("entry", "leave", "begun")))
    joined = table.frame.where("long").join(ways, met).select("conv_id", "turns", "entry", "leave", "begun")
    return short.unionByName(joined).mapInArrow(emit, FRAGMENTS)


def rendered(fragments: DataFrame) -> DataFrame:
    """``conv_id``, ``text``: whole renderings, for conversations that fit a row."""
    parts = F.sort_array(F.collect_list(F.struct("position", (F.col("action") == "merge").alias("merged"), "turn", "rendered")))
    return fragments.groupBy("conv_id").agg(F.concat(F.array_join(F.transform(parts, lambda x: x["rendered"]), ""), F.lit("<|end|>\n")).alias("text"))
