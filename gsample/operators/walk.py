"""Random walk sampling by supersteps, and two relatives.

Drawing a vertex's out-edges at random without replacement is the same as following a
random order fixed in advance.  So ``prepare`` ranks each vertex's out-edges once and
writes them in parts that follow from (vertex, rank), sorted inside; a walker that stands
on a vertex from which n edges were taken looks up edge n + 1.

Walks that visit up to ``DRIVEN`` vertices are driven from the driver: it holds the
walkers, what each vertex was left by and what was visited, all of bounded size, and a
superstep is one job that reads the parts that hold the walkers' edges, with their vertices
pushed down to the scan.  What chance decides is drawn for many supersteps at once.

Longer walks have as many walkers as a thirtieth of their target, so that a superstep moves
a good share of the graph: there it is a join of the walkers with the ranked edges, whose
state is in the shared folder.  Other kinds of memory and adjacency walk that way as well.
"""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil, log

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.randomness import drawn, unit_random
from ..plans.materialize import materialize
from ..plans.ranking import rank_within, smallest
from .model import PropertyGraph, drop_isolated, endpoints, induce

#: Supersteps after which the state's lineage is cut.
CUT = 5
#: Walkers that the driver may hold, and vertices to visit up to which it drives a walk.
LOCAL, DRIVEN = 100_000, 1_000_000
#: Out-edges of each vertex that are prepared for a driven walk at first.
FIRST = 128
#: Vertices whose out-edges make a part, about, the parts at most, and ranks of a hub that share one.
PART_VERTICES, PARTS, SPAN = 25_000, 20_001, 100_000
#: Walkers and supersteps for which chance is drawn in one job, at most.
DRAWS = 200_000
#: Keys that are written into a filter; more are joined.
LITERALS = 1000
#: Edges up to which the driver holds a frontier's graph, 32 bytes each and their order.
HELD = 2_000_000


@dataclass(frozen=True)
class Prepared:
    """The graph in the form that walks need: a dense index of vertices and ranked out-edges."""

    index: DataFrame  # id, idx
    ranked: DataFrame  # src, rank, edge_id, dst, dst_idx, part
    size: int
    parts: int
    cut: frozenset = frozenset()  # vertices of which ``ranked`` has the first out-edges only


class _Beyond(Exception):
    """A walk that asks for an out-edge that was not prepared."""


def _first_edges(edges: DataFrame, seed: int, source: str, first: int) -> tuple[DataFrame, frozenset]:
    """The edges with about twice ``first`` of each vertex that has more, those of the smallest numbers; and these vertices."""
    many = materialize(edges.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") > 2 * first).select("src", (2.0 * first / F.col("n")).alias("share")), "many")
    if not 0 < many.count() <= DRIVEN:
        return edges, frozenset()
    kept = edges.join(F.broadcast(many), "src", "left").where(F.col("share").isNull() | drawn(F.col("share"), seed, "edge", "edge_id", source))
    return materialize(kept.select(edges.columns), "first"), frozenset(many.select("src").toArrow().column("src").to_pylist())


def ranked_out_edges(edges: DataFrame, seed: int, source: str = "portable", hub: int = 1_000_000) -> DataFrame:
    """(src, edge_id, dst, rank): each vertex's out-edges numbered from 1 in a random order fixed by the seed.

    The edges of a vertex with over ``hub`` of them are numbered in 64 slices of the random
    number, which are tasks of their own; the slices' counts shift the numbers.  The order is
    the same as without slices.
    """
    e = edges.select("src", "edge_id", "dst").withColumn("u", unit_random(seed, "edge", "edge_id", source=source))
    hubs = materialize(edges.groupBy("src").agg(F.count("*").alias("n")).where(F.col("n") > hub).select("src"), "hubs")
    if hubs.isEmpty():
        order = Window.partitionBy("src").orderBy("u", "edge_id")
        return e.withColumn("rank", F.row_number().over(order)).drop("u")
    e = e.join(hubs.withColumn("hub", F.lit(True)), "src", "left").withColumn("slice", F.when(F.col("hub"), F.floor(F.col("u") * 64)).otherwise(0))
    local = materialize(e.withColumn("rank", F.row_number().over(Window.partitionBy("src", "slice").orderBy("u", "edge_id"))), "slices")
    before = Window.partitionBy("src").orderBy("slice").rowsBetween(Window.unboundedPreceding, -1)
    shift = local.where("hub").groupBy("src", "slice").agg(F.count("*").alias("n")).withColumn("shift", F.sum("n").over(before)).drop("n")
    joined = local.join(shift, ["src", "slice"], "left")
    return joined.select("src", "edge_id", "dst", (F.col("rank") + F.coalesce("shift", F.lit(0))).cast("int").alias("rank"))


def prepare(g: PropertyGraph, seed: int, source: str = "portable", hub: int = 1_000_000, first: int | None = None) -> Prepared:
    """``first``: of vertices with many out-edges only so many of the first, at least about."""
    size = g.vertices.count()
    numbers = g.vertices.select("id", unit_random(seed, "index", "id", source=source).alias("u"))
    index = rank_within(numbers, [], ["u", "id"], "idx", max(64, size // 1_000_000), unit=F.col("u"))
    index = materialize(index.select("id", "idx"), "index")
    edges, cut = (g.edges, frozenset()) if first is None else _first_edges(g.edges, seed, source, first)
    ranked = ranked_out_edges(edges, seed, source, hub).join(index.toDF("dst", "dst_idx"), "dst").select("src", "rank", "edge_id", "dst", "dst_idx")
    parts = min(PARTS, size // PART_VERTICES) | 1
    ranked = ranked.withColumn("part", F.pmod(F.col("src") + F.floor(F.col("rank") / SPAN), F.lit(parts)).cast("int"))
    ranked = ranked.repartition(parts, "part").sortWithinPartitions("part", "src", "rank")
    return Prepared(index, materialize(ranked, "ranked", ["part"]), size, parts, cut)


def _jump_target(seed: int, size: int, source: str):
    """The index of any other vertex than the walker's own."""
    t = F.floor(unit_random(seed, "to", "walker", "step", source=source) * max(size - 1, 1)).cast("long")
    return F.when(t >= F.col("at_idx"), t + 1).otherwise(t) if size > 1 else F.lit(0).cast("long")


def _land(p: Prepared, w: DataFrame, moved: DataFrame, step: int, seed: int, source: str, few) -> DataFrame:
    """(walker, at, at_idx, kind, src, edge_id): the walkers that moved along an edge, and the others after a jump."""
    w = w.join(few(moved), "walker", "left")  # a row per walker at most
    jumpers = w.where("dst is null").withColumn("idx", _jump_target(seed, p.size, source))
    landed = p.index.join(few(jumpers.select("walker", "idx", "chance")), "idx")
    kind, none = F.when(F.col("chance"), "jump").otherwise("stuck"), F.lit(None).cast("long")
    walked = w.where("dst is not null").select("walker", F.col("dst").alias("at"), F.col("dst_idx").alias("at_idx"), F.lit("walk").alias("kind"), F.col("at").alias("src"), "edge_id")
    return walked.union(landed.select("walker", F.col("id"), F.col("idx"), kind, none, none))


def _shared_step(p: Prepared, walkers: DataFrame, gone: DataFrame, step: int, seed: int, jump: float, source: str, few) -> DataFrame:
    """One superstep with edge marks shared by all walkers; ``gone``: (src, n) departures so far; ``few`` marks tables of a row per walker."""
    w = walkers.select("walker", "at", "at_idx").withColumn("step", F.lit(step)).withColumn("chance", unit_random(seed, "jump", "walker", "step", source=source) <= jump)
    turn = F.row_number().over(Window.partitionBy("at", "chance").orderBy("walker"))
    here = few(walkers.select(F.col("at").alias("src")).distinct())
    left = gone.join(here, "src", "left_semi").groupBy("src").agg(F.sum("n").alias("n"))  # a row per walker at most
    w = w.join(few(left.toDF("at", "n")), "at", "left").withColumn("want", F.coalesce("n", F.lit(0)) + turn).drop("n")
    go = w.where("not chance").select("walker", F.col("at").alias("src"), F.col("want").alias("rank"))
    moved = p.ranked.join(few(go), ["src", "rank"]).select("walker", "edge_id", "dst", "dst_idx")
    return _land(p, w, moved, step, seed, source, few)


def _scan_step(p: Prepared, walkers: DataFrame, gone: DataFrame, step: int, seed: int, jump: float, source: str, few) -> DataFrame:
    """The shared superstep without departures: every out-edge of the walkers' vertices is looked at, traversed ones are taken out.

    For comparison: its work follows the degrees, that of ``_shared_step`` the walkers.
    ``gone``: (src, edge_id) traversed so far.
    """
    w = walkers.select("walker", "at", "at_idx").withColumn("step", F.lit(step)).withColumn("chance", unit_random(seed, "jump", "walker", "step", source=source) <= jump)
    turn = F.row_number().over(Window.partitionBy("at", "chance").orderBy("walker"))
    w = w.withColumn("turn", turn)
    here = few(w.where("not chance").select(F.col("at").alias("src")).distinct())
    left = p.ranked.join(here, "src").join(gone.select("edge_id"), "edge_id", "left_anti")
    left = left.withColumn("turn", F.row_number().over(Window.partitionBy("src").orderBy("rank"))).select("src", "turn", "edge_id", "dst", "dst_idx")
    go = few(w.where("not chance").select("walker", F.col("at").alias("src"), "turn"))
    moved = left.join(go, ["src", "turn"]).select("walker", "edge_id", "dst", "dst_idx")
    return _land(p, w.drop("turn"), moved, step, seed, source, few)


def _own_step(p: Prepared, walkers: DataFrame, gone: DataFrame, step: int, seed: int, jump: float, source: str, few) -> DataFrame:
    """One superstep with edge marks of each walker's own; ``gone``: (walker, edge_id) traversed so far."""
    w = walkers.select("walker", "at", "at_idx").withColumn("step", F.lit(step)).withColumn("chance", unit_random(seed, "jump", "walker", "step", source=source) <= jump)
    open_ = p.ranked.join(few(w.where("not chance").select("walker", F.col("at").alias("src"))), "src").join(gone, ["walker", "edge_id"], "left_anti")
    key = F.struct(unit_random(seed, "edge", "walker", "edge_id", source=source), F.col("edge_id"))
    moved = open_.groupBy("walker").agg(F.min_by(F.struct("edge_id", "dst", "dst_idx"), key).alias("m")).select("walker", "m.*")
    return _land(p, w, moved, step, seed, source, few)


class _Draws:
    """What chance says of every walker in each superstep, drawn for a block of supersteps in one job."""

    def __init__(self, p: Prepared, seed: int, walkers: int, jump: float, source: str):
        self.p, self.seed, self.walkers, self.jump, self.source = p, seed, walkers, jump, source
        self.first = self.end = 0

    def at(self, step: int) -> tuple[np.ndarray, np.ndarray]:
        """By walker: whether it jumps by chance, and the drawn place of a jump."""
        if not self.first <= step < self.end:
            self._draw(step)
        return self.chance[step - self.first], self.to[step - self.first]

    def _draw(self, step: int) -> None:
        steps, p = max(1, min(64, DRAWS // self.walkers)), self.p
        walker, number = (F.col("id") % self.walkers).cast("int").alias("walker"), (F.floor(F.col("id") / self.walkers) + step).cast("int").alias("step")
        rows = p.index.sparkSession.range(self.walkers * steps).coalesce(8).select("id", walker, number)
        to = F.floor(unit_random(self.seed, "to", "walker", "step", source=self.source) * max(p.size - 1, 1)).cast("long")
        drawn = rows.select("id", (unit_random(self.seed, "jump", "walker", "step", source=self.source) <= self.jump).alias("chance"), to.alias("to")).toArrow()
        order = np.argsort(drawn.column("id").to_numpy())
        self.chance, self.to = (drawn.column(c).to_numpy()[order].reshape(steps, -1) for c in ("chance", "to"))
        self.first, self.end = step, step + steps
        wanted = np.unique(np.r_[self.to.ravel(), self.to.ravel() + 1])
        found = p.index.join(F.broadcast(p.index.sparkSession.createDataFrame(pa.table({"idx": wanted}))), "idx").toArrow()
        self.ids = dict(zip(found.column("idx").to_pylist(), found.column("id").to_pylist(), strict=True))


def departures(p: Prepared, keys: list[tuple[int, int]]) -> DataFrame:
    """(src, rank, edge_id, dst, dst_idx) of the given (src, rank), and few others: only the parts that can hold them are read."""
    parts = sorted({(src + rank // SPAN) % p.parts for src, rank in keys})
    some = p.ranked.where(f"part IN ({', '.join(map(str, parts))})")
    if len(keys) <= LITERALS:
        src, rank = ({k[i] for k in keys} for i in (0, 1))
        some = some.where(f"src IN ({', '.join(map(str, src))}) AND rank IN ({', '.join(map(str, rank))})")
    else:
        frame = p.ranked.sparkSession.createDataFrame(keys, "src bigint, rank int")
        some = some.join(F.broadcast(frame), ["src", "rank"], "left_semi")
    return some.select("src", "rank", "edge_id", "dst", "dst_idx")


def _driven(p: Prepared, start: DataFrame, target: int, seed: int, walkers: int, jump: float, stop: str, on_meet: str, max_supersteps: int, source: str) -> DataFrame | None:
    """The trace of a walk with shared marks that the driver drives; None if it misses the target."""
    draws = _Draws(p, seed, walkers, jump, source)
    now = {r["walker"]: (r["at"], r["at_idx"]) for r in start.collect()}
    trace = [(w, 0, at, "start") for w, (at, _) in now.items()]
    tables: list[DataFrame] = []
    visited, gone = {at for at, _ in now.values()}, {}
    shape = "walker int, step int, at bigint, kind string"

    def cut() -> None:
        columns = zip(*trace, strict=True) if trace else ([], [], [], [])
        kinds = (pa.int32(), pa.int32(), pa.int64(), pa.string())
        rows = pa.table([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["walker", "step", "at", "kind"])
        tables.append(materialize(p.index.sparkSession.createDataFrame(rows, shape).coalesce(1), "trace"))
        trace.clear()

    for step in range(1, max_supersteps + 2):
        if p.size == 0 or (len(visited) >= target if stop == "reach" else len(visited) > target):
            cut()
            whole = tables[0]
            for t in tables[1:]:
                whole = whole.union(t)
            return whole
        if step > max_supersteps:
            return None
        chance, to = draws.at(step)
        turn: dict[int, int] = {}
        wish: dict[int, tuple[int, int]] = {}
        for w in sorted(now):
            if not chance[w]:
                src = now[w][0]
                turn[src] = turn.get(src, 0) + 1
                wish[w] = (src, gone.get(src, 0) + turn[src])
        arms = {(r["src"], r["rank"]): (r["dst"], r["dst_idx"]) for r in departures(p, list(wish.values())).collect()} if wish else {}
        then: dict[int, tuple[int, int]] = {}
        met: set[int] = set()
        for w in sorted(now):
            at, idx = now[w]
            arm = arms.get(wish[w]) if w in wish else None
            if arm is None and w in wish and at in p.cut:
                raise _Beyond
            if arm is not None:
                gone[at], kind = gone.get(at, 0) + 1, "walk"
            else:
                place = (int(to[w]) + (to[w] >= idx)) if p.size > 1 else 0
                arm, kind = (draws.ids[place], place), "jump" if chance[w] else "stuck"
            if on_meet == "merge" and arm[0] in met:
                continue
            met.add(arm[0])
            then[w] = arm
            trace.append((w, step, arm[0], kind))
        now = then
        visited |= met
        if len(trace) > DRIVEN:
            cut()
    return None


def walkers_for(target: int) -> int:
    """A thirtieth of the vertices to visit, so that supersteps stay few at any size."""
    return max(1, ceil(target / 30))


def _starts(p: Prepared, walkers: int, seed: int, source: str) -> DataFrame:
    """(walker, at, at_idx): the vertices with the smallest numbers, walkers numbered in that order."""
    u = unit_random(seed, "start", "id", source=source)
    if walkers <= LOCAL:
        first = p.index.orderBy(u, "id").limit(walkers)
        ranked = first.withColumn("walker", F.row_number().over(Window.orderBy(u, "id")) - 1)
    else:
        first = smallest(p.index, u, "id", walkers).withColumn("u", u)
        ranked = rank_within(first, [], ["u", "id"], "walker", max(64, walkers // 1_000_000), unit=F.col("u"))
    return ranked.select(F.col("walker").cast("int").alias("walker"), F.col("id").alias("at"), F.col("idx").alias("at_idx"))


def walk_trace(g: PropertyGraph, target: int, seed: int = 7, walkers: int = 1, jump: float = 0.1, edge_memory: str = "shared", stop: str = "reach", on_meet: str = "keep", max_supersteps: int = 10_000, source: str = "portable", prepared: Prepared | None = None, adjacency: str = "ranked", driven: bool = True) -> DataFrame:
    """(walker, step, at, kind): where every walker was after each superstep, from the start (step 0) to the stop.

    The walk stops at the first superstep after which ``target`` vertices were visited
    ('reach') or more than that ('exceed').  ``on_meet='merge'`` lets one of several walkers
    on a vertex go on.  ``adjacency='scan'`` looks at all out-edges instead of the ranked one,
    ``driven=False`` joins at any size; the walk is the same.  A walk that cannot or does not
    get there within ``max_supersteps`` raises an error.
    """
    p = prepared or prepare(g, seed, source)
    target = min(target, p.size - (stop == "exceed"))
    missed = RuntimeError(f"fewer than {target + (stop == 'exceed')} vertices in {max_supersteps} supersteps of {walkers} walkers")
    if walkers * (max_supersteps + 1) < target + (stop == "exceed"):
        raise missed
    first = _starts(p, walkers, seed, source)
    shared, scan = edge_memory == "shared", edge_memory == "shared" and adjacency == "scan"
    if driven and shared and not scan and walkers <= LOCAL and target <= DRIVEN:
        trace = _driven(p, first, target, seed, walkers, jump, stop, on_meet, max_supersteps, source)
        if trace is None:
            raise missed
        return trace
    none = F.lit(None).cast("long")
    start = first.select("walker", F.lit(0).alias("step"), "at", "at_idx", F.lit("start").alias("kind"), none.alias("src"), none.alias("edge_id"))
    hold = _Holder(g.spark, walkers)
    now, step = hold.keep(start), 0
    gone = g.spark.createDataFrame([], "src bigint, edge_id bigint" if scan else "src bigint, n bigint" if shared else "walker int, edge_id bigint")
    sure = 0  # before this superstep even fresh vertices only cannot reach the target
    while True:
        if step >= sure:
            n = hold.trace().select("at").distinct().count()
            if p.size == 0 or (n >= target if stop == "reach" else n > target):
                return hold.trace().select("walker", "step", "at", "kind")
            sure = step + max(1, -(-(target - n + (stop == "exceed")) // max(walkers, 1)))
        if step >= max_supersteps:
            raise missed
        step += 1
        moves = (_scan_step if scan else _shared_step if shared else _own_step)(p, now, gone, step, seed, jump, source, F.broadcast if hold.local else lambda df: df)
        if on_meet == "merge":
            keep = F.row_number().over(Window.partitionBy("at").orderBy("walker"))
            moves = moves.withColumn("k", keep).where("k = 1").drop("k")
        now = hold.keep(moves.select("walker", F.lit(step).alias("step"), "at", "at_idx", "kind", "src", "edge_id"))
        left = now.where("edge_id is not null")
        if scan:
            gone = gone.union(left.select("src", "edge_id"))
        elif shared:
            gone = gone.union(left.groupBy("src").agg(F.count("*").alias("n")))
        else:
            gone = gone.union(left.select("walker", "edge_id"))
        if step % CUT == 0:
            gone = gone.groupBy("src").agg(F.sum("n").alias("n")) if shared and not scan else gone
            gone = materialize(gone.coalesce(1 + walkers * step // 1_000_000), "gone")


class _Holder:
    """The walkers after each superstep.

    Up to ``LOCAL`` walkers the driver holds their latest rows; what they did goes to the
    shared folder every few supersteps.  More walkers are written at each superstep.
    """

    def __init__(self, spark, walkers: int):
        self.spark, self.local = spark, walkers <= LOCAL
        self.fresh: list[pa.Table] = []
        self.tables: list[DataFrame] = []

    def keep(self, rows: DataFrame) -> DataFrame:
        if not self.local:
            self.tables.append(materialize(rows, "walkers"))
            return self.tables[-1]
        self.fresh.append(rows.toArrow())
        now = self.spark.createDataFrame(self.fresh[-1]).coalesce(1)
        if len(self.fresh) >= 4 * CUT:
            self.tables.append(materialize(self.spark.createDataFrame(pa.concat_tables(self.fresh)).coalesce(1), "trace"))
            self.fresh = []
        return now

    def trace(self) -> DataFrame:
        parts = [*self.tables, *([self.spark.createDataFrame(pa.concat_tables(self.fresh))] if self.fresh else [])]
        whole = parts[0]
        for part in parts[1:]:
            whole = whole.union(part)
        return whole


def random_walk(g: PropertyGraph, s: float | None = None, seed: int = 7, walkers: int | None = None, jump: float = 0.1, target: int | None = None, edge_memory: str = "shared", stop: str = "reach", on_meet: str = "keep", max_supersteps: int = 10_000, source: str = "portable", keep_isolated: bool = False) -> PropertyGraph:
    """The visited vertices and all edges between them; ``s`` or ``target`` says how many to visit, and, by ``walkers_for``, the walkers if none are given.

    A driven walk takes few of a vertex's out-edges, so at first about twice ``FIRST`` are
    prepared where they are many; a walk that asks for more begins again with all of them.
    """
    size = g.vertices.count()
    wanted = target if target is not None else ceil(s * size)
    walkers = walkers_for(min(wanted, size)) if walkers is None else walkers
    few = edge_memory == "shared" and walkers <= LOCAL and wanted <= DRIVEN

    def walked(first: int | None) -> DataFrame:
        return walk_trace(g, wanted, seed, walkers, jump, edge_memory, stop, on_meet, max_supersteps, source, prepare(g, seed, source, first=first))

    try:
        trace = walked(FIRST if few else None)
    except _Beyond:
        trace = walked(None)
    sample = induce(g, materialize(trace.select(F.col("at").alias("id")).distinct(), "visited"))
    sample = PropertyGraph(sample.vertices, materialize(sample.edges, "sample"))  # both tables of the result read the edges
    return sample if keep_isolated else drop_isolated(sample)


def walk_counters(trace: DataFrame) -> DataFrame:
    """(supersteps, walks, chance_jumps, stuck_jumps, visited) of a trace."""
    of = lambda kind: F.sum((F.col("kind") == kind).cast("long"))
    return trace.agg(F.max("step").alias("supersteps"), of("walk").alias("walks"), of("jump").alias("chance_jumps"), of("stuck").alias("stuck_jumps"), F.countDistinct("at").alias("visited"))


def frontier(g: PropertyGraph, s: float, seed: int = 7, dims: int = 32, max_supersteps: int = 10_000, steps_per_job: int = 4, source: str = "portable") -> PropertyGraph:
    """Frontier sampling: of ``dims`` dependent walkers, the next to step is chosen by degree.

    That choice equals independent walkers whose waiting times are exponential with their
    vertex's degree as rate, so all step in parallel with a clock each; the order in time is
    the order of the dependent process.  The sample is made of the edges passed, in that
    order, until ``s`` of the vertices were visited.

    Every superstep looks up an arm of each walker.  Up to ``HELD`` edges the driver does that,
    with what chance says drawn for many supersteps in a job; more are joined with the walkers.
    """
    u = g.edges.where("src <> dst")
    if dims <= LOCAL and u.limit(HELD + 1).count() <= HELD:
        return _held_frontier(g, u, s, seed, dims, -(-max_supersteps // steps_per_job) * steps_per_job, source)
    arms = u.select(F.col("src").alias("v"), F.col("dst").alias("o"), "edge_id").union(u.select("dst", "src", "edge_id"))
    numbered = ranked_out_edges(arms.toDF("src", "dst", "edge_id"), seed, source).select(F.col("src").alias("v"), F.col("dst").alias("o"), "edge_id", (F.col("rank") - 1).alias("rank"))
    numbered = materialize(numbered, "arms")
    # a hub's arms are counted before the shuffle, and only its first arm needs the count
    degrees = numbered.groupBy("v").agg(F.count("*").alias("degree"))
    starts = materialize(numbered.where("rank = 0").select("v").join(degrees, "v"), "degrees")
    target = ceil(s * g.vertices.count())
    first = starts.orderBy(unit_random(seed, "start", "v", source=source), "v").limit(dims)
    now = materialize(first.select((F.row_number().over(Window.orderBy(unit_random(seed, "start", "v", source=source), "v"))).alias("walker"), "v", "degree", F.lit(0.0).alias("time")), "walkers")
    log, step = now.select("walker", F.lit(0).alias("step"), F.col("time"), F.lit(None).cast("long").alias("edge_id"), "v"), 0
    log = materialize(log, "trace")
    while step < max_supersteps:
        for _ in range(steps_per_job):
            step += 1
            draw = now.withColumn("step", F.lit(step))
            wait = -F.log(1 - unit_random(seed, "wait", "walker", "step", source=source)) / F.col("degree")
            draw = draw.select("walker", "v", (F.col("time") + wait).alias("time"), F.floor(unit_random(seed, "arm", "walker", "step", source=source) * F.col("degree")).alias("rank"))
            passed = numbered.join(F.broadcast(draw), ["v", "rank"])  # a row per walker
            now = starts.join(F.broadcast(passed.select("walker", F.col("o").alias("v"), "time", "edge_id")), "v")
            log = log.union(now.select("walker", F.lit(step), "time", "edge_id", "v"))
            now = now.select("walker", "v", "degree", "time")
        log, now = materialize(log, "trace"), materialize(now, "walkers")
        sure = now.agg(F.min("time")).first()[0]  # before this moment no walker can add a passage
        known = log if sure is None else log.where(F.col("time") <= sure)
        firsts = known.groupBy("v").agg(F.min("time").alias("time"))
        if sure is None or firsts.count() >= target:
            end = smallest(firsts, F.col("time"), "v", target, 0.0, sure).agg(F.max("time")).first()[0] if sure is not None else None
            known = known if end is None else known.where(F.col("time") <= end)
            edges = g.edges.join(known.select("edge_id").where("edge_id is not null").distinct(), "edge_id", "left_semi")
            return drop_isolated(PropertyGraph(g.vertices, edges.select(g.edges.columns)))
    raise RuntimeError(f"fewer than {target} vertices in {max_supersteps} supersteps")


def _held_frontier(g: PropertyGraph, u: DataFrame, s: float, seed: int, dims: int, max_supersteps: int, source: str) -> PropertyGraph:
    """``frontier`` over the edges ``u``, which the driver holds."""
    target = ceil(s * g.vertices.count())
    held = u.select("src", "dst", "edge_id", unit_random(seed, "edge", "edge_id", source=source).alias("u")).toArrow()
    src, dst, edge, drawn_ = (held.column(c).to_numpy() for c in held.column_names)
    ids, ends = np.unique(np.concatenate([src, dst]), return_inverse=True)
    order = np.lexsort((np.tile(edge, 2), np.tile(drawn_, 2), ends))
    degree = np.bincount(ends, minlength=len(ids))
    begin, arm = np.r_[0, np.cumsum(degree)], order % max(len(edge), 1)
    over = ends[(order + len(edge)) % max(len(order), 1)]  # the other end of each arm
    number = unit_random(seed, "start", "id", source=source)
    first = [r["id"] for r in endpoints(u).orderBy(number, "id").limit(dims).collect()]
    at, time, step = np.searchsorted(ids, np.array(first, np.int64)), np.zeros(len(first)), 0
    times, passed, reached = [time], [np.full(len(first), -1)], [at]
    some = np.zeros(0, np.int64)
    while len(first):
        if step >= max_supersteps:
            raise RuntimeError(f"fewer than {target} vertices in {max_supersteps} supersteps")
        steps = min(max(64, step // 4), max(1, DRAWS // dims), max_supersteps - step)
        for wait, choice in zip(*_waits(g, seed, len(first), step + 1, steps, source), strict=True):
            time = time + wait / degree[at]
            chosen = begin[at] + np.floor(choice * degree[at]).astype(np.int64)
            at = over[chosen]
            times.append(time)
            passed.append(arm[chosen])
            reached.append(at)
        step += steps
        when, through, where = (np.concatenate(x) for x in (times, passed, reached))
        known = np.flatnonzero(when <= time.min())  # before this moment no walker can add a passage
        firsts = np.full(len(ids), np.inf)
        np.minimum.at(firsts, where[known], when[known])
        firsts = np.sort(firsts[np.isfinite(firsts)])
        if len(firsts) >= target:
            some = through[known[when[known] <= (firsts[target - 1] if target else -1.0)]]
            break
    taken = materialize(g.spark.createDataFrame(pa.table({"edge_id": np.unique(edge[some[some >= 0]])})), "taken")
    edges = g.edges.join(taken, "edge_id", "left_semi")
    return drop_isolated(PropertyGraph(g.vertices, edges.select(g.edges.columns)))


def _waits(g: PropertyGraph, seed: int, walkers: int, step: int, steps: int, source: str) -> tuple[np.ndarray, np.ndarray]:
    """By superstep and walker, from 1: the waiting time at rate 1, and the number that chooses the arm."""
    walker, number = (F.col("id") % walkers + 1).cast("int").alias("walker"), (F.floor(F.col("id") / walkers) + step).cast("int").alias("step")
    rows = g.spark.range(walkers * steps).coalesce(8).select("id", walker, number)
    wait = -F.log(1 - unit_random(seed, "wait", "walker", "step", source=source))
    got = rows.select("id", wait.alias("wait"), unit_random(seed, "arm", "walker", "step", source=source).alias("arm")).toArrow()
    order = np.argsort(got.column("id").to_numpy())
    return tuple(got.column(c).to_numpy()[order].reshape(steps, -1) for c in ("wait", "arm"))


def forest_fire(g: PropertyGraph, s: float, seed: int = 7, p_forward: float = 0.7, p_backward: float = 0.2, fires: int = 8, max_supersteps: int = 10_000, source: str = "portable") -> PropertyGraph:
    """Forest-fire sampling: fires spread from burning vertices to geometrically many unburnt neighbours.

    Out-edges burn with ``p_forward``, in-edges with ``p_backward``; where all fires die, new
    ones start among unburnt vertices.  The sample is induced on the first ``s`` of the
    vertices to burn, by superstep and then by hash.
    """
    target, burnt, step = ceil(s * g.vertices.count()), None, 0
    ids = materialize(g.vertices.select("id"), "ids")
    arms = materialize(g.edges.where("src <> dst").select(F.col("src").alias("id"), F.col("dst").alias("o"), F.lit("f").alias("way")).union(g.edges.where("src <> dst").select("dst", "src", F.lit("b"))).distinct(), "arms")
    front = None
    while step < max_supersteps:
        if front is None or front.isEmpty():
            left = ids if burnt is None else ids.join(burnt, "id", "left_anti")
            front = left.orderBy(unit_random(seed + step, "fire", "id", source=source), "id").limit(fires)
        fresh = front.select("id", F.lit(step).alias("step"))
        burnt = materialize(fresh if burnt is None else burnt.union(fresh), "burnt")
        many = burnt.count()
        if many >= target:
            before = burnt.where(F.col("step") < step)
            last = smallest(burnt.where(F.col("step") == step), unit_random(seed, "burn", "id", source=source), "id", target - before.count())
            return drop_isolated(induce(g, before.unionByName(last).select("id")))
        front = burnt.where(F.col("step") == step).select("id")
        step += 1
        chance = F.when(F.col("way") == "f", F.lit(p_forward)).otherwise(F.lit(p_backward))
        draw = F.floor(F.log(1 - unit_random(seed, "spread", "id", "way", source=source)) / F.log(chance))
        live = arms.join(front, "id").join(burnt.select(F.col("id").alias("o")), "o", "left_anti")
        turn = F.row_number().over(Window.partitionBy("id", "way").orderBy(unit_random(seed, "arm", "id", "o", "way", source=source), "o"))
        # no drawn number is above this one, so a hub's task sees few arms of each other task
        most = 1 + int(37 / -log(max(p_forward, p_backward)))
        front = materialize(live.withColumn("turn", turn).where(F.col("turn") <= most).withColumn("many", draw).where("turn <= many").select(F.col("o").alias("id")).distinct(), "front")
    raise RuntimeError("the fires did not burn enough")
