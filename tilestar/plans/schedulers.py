"""Seven message schedulers on a star platform, simulated event by event over tables of scenarios.

A chunk's life: its C square arrives, then panels of A and B for all inner steps, then the square returns. The port carries one message at a time (two_port: sends
and returns have a port each). A message takes its tiles times c, an update w. With spare buffers one panel may arrive while another is computed on, so panel n+1
may start when panel n-1 is done; without, when panel n is done. Chunks are dealt down a chunk column, then the next; ragged ones keep their size.

One scenario is sequential; the table of scenarios is partitioned.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: name: layout, whether panels overlap with computation
POLICIES = {
    "rr_selected": ("overlap", True), "rr_all": ("overlap", True), "minmin_overlap": ("overlap", True), "demand_overlap": ("overlap", True),
    "demand_plain": ("plain", False), "third_demand": ("third", False), "fifth_demand": ("fifth", True),
}
SUMMARY = "scenario_id int, policy string, workers_used int, tiles bigint, makespan bigint, port_busy bigint, updates bigint"
TRACE = "scenario_id int, policy string, step int, worker_id int, kind string, ci int, cj int, k int, start bigint, finish bigint, work_start bigint, work_finish bigint, tiles bigint"


def _root(x: int) -> int:
    s = int(x**0.5)
    while s * s > x:
        s -= 1
    while (s + 1) * (s + 1) <= x:
        s += 1
    return s


def side(layout: str, m: int) -> int:
    return {"overlap": lambda: _root(m + 4) - 2, "plain": lambda: _root(m + 1) - 1, "third": lambda: _root(m // 3), "fifth": lambda: _root(m // 5)}[layout]()


@dataclass
class Worker:
    c: int
    w: int
    g: int
    chunk: tuple[int, int, int, int] | None = None  # ci, cj, height, width
    stage: int = -1  # -1: C square next; then the panel's number; then the return
    panels: list[int] = field(default_factory=list)  # inner steps of each panel
    done: list[int] = field(default_factory=lambda: [0, 0])  # when the last two panels' computing ends
    free: int = 0


class Run:
    """State of one scenario."""

    def __init__(self, r: int, t: int, s: int, workers: list[Worker], layout: str, overlap: bool, two_port: bool) -> None:
        self.r, self.t, self.s, self.workers, self.overlap, self.two_port = r, t, s, workers, overlap, two_port
        self.square = layout in ("third", "fifth")
        self.port = [0, 0]
        self.todo: list[tuple[int, int, int, int]] = []
        self.rows: list[tuple] = []
        self.busy = self.tiles = self.updates = 0

    def deal(self, g: int, columns: Iterator[int] | None = None) -> list[tuple[int, int, int, int]]:
        cols = columns if columns is not None else range(-(-self.s // g))
        return [(ci, cj, min(g, self.r - ci * g), min(g, self.s - cj * g)) for cj in cols for ci in range(-(-self.r // g))]

    def take(self, x: Worker, chunk: tuple[int, int, int, int]) -> None:
        x.chunk, x.stage = chunk, -1
        step = x.g if self.square else 1
        x.panels = [min(step, self.t - k) for k in range(0, self.t, step)]
        x.done = [x.free, x.free]

    def peek(self, x: Worker, chunk: tuple[int, int, int, int]) -> tuple[str, int, int]:
        """Kind, tiles and earliest start of a worker's next message."""
        _, _, a, b = chunk
        if x.chunk is None or x.stage == -1:
            return "C", a * b, x.free
        if x.stage < len(x.panels):
            return "P", x.panels[x.stage] * (a + b), x.done[0] if self.overlap else x.done[1]
        return "R", a * b, x.done[1]

    def send(self, n: int) -> None:
        x = self.workers[n]
        kind, tiles, ready = self.peek(x, x.chunk)
        gate = 1 if self.two_port and kind == "R" else 0
        start = max(self.port[gate], ready)
        end = start + tiles * x.c
        self.port[gate] = end
        if not self.two_port:
            self.port[1] = end
        self.busy += end - start
        self.tiles += tiles
        ci, cj, a, b = x.chunk
        begin = finish = end
        if kind == "P":
            begin = max(end, x.done[1])
            finish = begin + a * b * x.panels[x.stage] * x.w
            self.updates += a * b * x.panels[x.stage]
            x.done = [x.done[1], finish]
        elif kind == "C":
            x.done = [end, end]
        self.rows.append((len(self.rows) + 1, n + 1, kind, ci, cj, x.stage if kind == "P" else -1, start, end, begin, finish, tiles))
        x.stage += 1
        if kind == "R":
            x.chunk, x.free = None, end


def _cyclic(run: Run, p: int) -> None:
    """Rounds of P chunks in one chunk row: P squares, P panels for each inner step, P returns."""
    g = min(x.g for x in run.workers)
    n_cols = -(-run.s // g)
    for first in range(0, n_cols, p):
        columns = range(first, min(n_cols, first + p))
        for ci in range(-(-run.r // g)):
            for n, cj in enumerate(columns):
                run.take(run.workers[n], (ci, cj, min(g, run.r - ci * g), min(g, run.s - cj * g)))
            for _ in range(run.t + 2):
                for n in range(len(columns)):
                    run.send(n)


def _greedy(run: Run, earliest_end: bool) -> None:
    """Every step the best next message of any worker: by its end (static min-min), or by its start and then the worker's own readiness."""
    g = min(x.g for x in run.workers)
    run.todo = run.deal(g)[::-1]
    while run.todo or any(x.chunk for x in run.workers):
        best = None
        for n, x in enumerate(run.workers):
            chunk = x.chunk or (run.todo[-1] if run.todo else None)
            if chunk is None:
                continue
            kind, tiles, ready = run.peek(x, chunk)
            start = max(run.port[1 if run.two_port and kind == "R" else 0], ready)
            if earliest_end:
                end = start + tiles * x.c
                key = (max(end, x.done[1]) if kind == "P" else end, n)
            else:
                key = (start, ready, n)
            if best is None or key < best:
                best = key
        n = best[-1]
        if run.workers[n].chunk is None:
            run.take(run.workers[n], run.todo.pop())
        run.send(n)


def play(policy: str, r: int, t: int, s: int, platform: list[tuple[int, int, int]], two_port: bool = False) -> Run:
    """platform: (c, w, m) of each worker, in order of id."""
    layout, overlap = POLICIES[policy]
    workers = [Worker(c, w, side(layout, m)) for c, w, m in platform]
    workers = [x for x in workers if x.g >= 1]
    if not workers:
        raise ValueError("no worker has the buffers of a 1 x 1 chunk")
    run = Run(r, t, s, workers, layout, overlap, two_port)
    if policy.startswith("rr"):
        # the closed form on the workers' mean times; with equal workers it is the closed form itself
        g, c, w = min(x.g for x in workers), sum(x.c for x in workers), sum(x.w for x in workers)
        p = min(len(workers), -(-g * w // (2 * c))) if policy == "rr_selected" else len(workers)
        _cyclic(run, p)
    else:
        _greedy(run, policy == "minmin_overlap")
    return run


def simulate(scenarios: DataFrame, trace: bool = False) -> DataFrame:
    """scenarios (scenario_id, policy, r, t, s, port, platform array<struct<c,w,m>>) -> SUMMARY, or TRACE."""

    def go(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for x in b.itertuples():
                run = play(x.policy, x.r, x.t, x.s, [(w["c"], w["w"], w["m"]) for w in x.platform], x.port == "two_port")
                if trace:
                    rows = pd.DataFrame(run.rows, columns=["step", "worker_id", "kind", "ci", "cj", "k", "start", "finish", "work_start", "work_finish", "tiles"])
                    rows.insert(0, "policy", x.policy)
                    rows.insert(0, "scenario_id", x.scenario_id)
                    yield rows
                else:
                    used = len({row[1] for row in run.rows})
                    end = max(max(row[7], row[9]) for row in run.rows)
                    yield pd.DataFrame([(x.scenario_id, x.policy, used, run.tiles, end, run.busy, run.updates)], columns=[f.split()[0] for f in SUMMARY.split(", ")])

    tasks = int(scenarios.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return scenarios.repartition(tasks, "scenario_id", "policy").mapInPandas(go, TRACE if trace else SUMMARY)


#: Block shapes (r, t, s) and buffers of the experiment sets.
SET_ONE = ((100, 100, 800, 10485), (200, 200, 1600, 10485), (100, 800, 800, 10485))
SET_MEMORY = ((200, 200, 800, 2703), (200, 200, 800, 5242), (200, 200, 800, 10485))


def scenarios(spark, shapes, policies=tuple(POLICIES), p: int = 8, c: int = 100, w: int = 7, port: str = "one_port") -> DataFrame:
    """Every policy on every shape (r, t, s, m), on p equal workers."""
    rows = [(n, policy, r, t, s, port, [(c, w, m)] * p) for n, (r, t, s, m) in enumerate(shapes) for policy in policies]
    return spark.createDataFrame(rows, "scenario_id int, policy string, r bigint, t bigint, s bigint, port string, platform array<struct<c:bigint,w:bigint,m:bigint>>")


def on_platforms(platform: DataFrame, r: int, t: int, s: int, policies=tuple(POLICIES)) -> DataFrame:
    """Every policy on every platform of a table. Round robin takes the workers in order of id, and all of them the chunk of the smallest."""
    own = platform.filter("m >= 12").groupBy("platform_id").agg(F.sort_array(F.collect_list(F.struct("worker_id", "c", "w", "m"))).alias("ws"))
    each = F.explode(F.array(*(F.lit(p) for p in policies))).alias("policy")
    fixed = [F.lit(x).cast("bigint").alias(n) for n, x in (("r", r), ("t", t), ("s", s))]
    shape = F.transform("ws", lambda x: F.struct(x["c"].alias("c"), x["w"].alias("w"), x["m"].alias("m"))).alias("platform")
    return own.select(F.col("platform_id").alias("scenario_id"), each, *fixed, F.lit("one_port").alias("port"), shape)


#: What holds in every trace: the port carries one message at a time; work waits for its panel; a return waits for the work; a worker holds no more than its memory;
#: every (chunk, inner step) comes once, and the chunks make up the result.
RULES = ("port", "early_work", "early_return", "memory", "once", "whole")


def violations(scenarios: DataFrame) -> DataFrame:
    """(rule, n): violations of RULES in the traces of one-port scenarios. Expected 0 each."""
    from pyspark.sql import Window

    traced = simulate(scenarios, trace=True)
    port = Window.partitionBy("scenario_id", "policy").orderBy("step")
    own = Window.partitionBy("scenario_id", "policy", "worker_id").orderBy("step")
    x = traced.withColumns({"free": F.lag("finish").over(port), "last": F.lag("work_finish").over(own)})
    bad = {"port": F.col("start") < F.col("free"), "early_work": F.col("work_start") < F.col("finish"), "early_return": (F.col("kind") == "R") & (F.col("start") < F.col("last"))}
    timing = x.agg(*(F.sum(F.when(cond, 1).otherwise(0)).cast("bigint").alias(k) for k, cond in bad.items()))
    # tiles come where a message starts to arrive, and go when a panel is worked off or a square is back
    kind = F.col("kind")
    come = traced.filter("kind <> 'R'").select("scenario_id", "policy", "worker_id", F.col("start").alias("at"), F.lit(1).alias("order"), F.col("tiles").alias("more"))
    go = traced.filter("kind <> 'C'").select(
        "scenario_id", "policy", "worker_id", F.when(kind == "P", F.col("work_finish")).otherwise(F.col("finish")).alias("at"), F.lit(0).alias("order"), (-F.col("tiles")).alias("more")
    )
    held = come.unionByName(go).withColumn("held", F.sum("more").over(Window.partitionBy("scenario_id", "policy", "worker_id").orderBy("at", "order").rowsBetween(Window.unboundedPreceding, 0)))
    has = scenarios.select("scenario_id", "policy", F.posexplode("platform").alias("n", "p")).select("scenario_id", "policy", (F.col("n") + 1).alias("worker_id"), "p.m")
    memory = held.join(has, ["scenario_id", "policy", "worker_id"]).agg(F.sum(F.when(F.col("held") > F.col("m"), 1).otherwise(0)).cast("bigint").alias("memory"))
    steps = traced.filter("kind = 'P'").groupBy("scenario_id", "policy", "ci", "cj", "k").count()
    once = steps.agg(F.sum(F.when(F.col("count") > 1, 1).otherwise(0)).cast("bigint").alias("once"))
    cells = traced.filter("kind = 'R'").groupBy("scenario_id", "policy").agg(F.sum("tiles").alias("returned"))
    updates = simulate(scenarios).select("scenario_id", "policy", "updates")
    shape = scenarios.select("scenario_id", "policy", (F.col("r") * F.col("s")).alias("cells"), (F.col("r") * F.col("t") * F.col("s")).alias("all"))
    whole = shape.join(cells, ["scenario_id", "policy"], "left").join(updates, ["scenario_id", "policy"], "left")
    whole = whole.agg(F.sum(F.when((F.col("returned") == F.col("cells")) & (F.col("updates") == F.col("all")), 0).otherwise(1)).cast("bigint").alias("whole"))
    one = timing.crossJoin(memory).crossJoin(once).crossJoin(whole)  # one row each
    return one.select(F.expr(f"stack({len(RULES)}, " + ", ".join(f"'{k}', {k}" for k in RULES) + ") as (rule, n)"))
