"""Greedy contiguous regionalization of many networks: one task for each network, or joins for a single huge one.

``run`` sends each network (flows, borders, units) to one task by one shuffle and returns its merge
path; partitions for any number of groups are cut from the path without running again.
"""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from flowregions.plans.checkpoints import cut
from flowregions.operators import dl
from flowregions.plans import kernel

TRAJECTORY = "network_id string, step int, b int, kept int, absorbed int, delta double, dl double"


def gathered(flows: DataFrame, units: DataFrame, adjacency: DataFrame) -> DataFrame:
    """All that a network's task needs, as one table: kind 0 units, 1 flows, 2 borders."""
    row = lambda df, kind, a, b, w: df.select("network_id", F.lit(kind).alias("kind"), F.col(a).cast("int").alias("a"), b.cast("int").alias("b"), w.cast("long").alias("w"))
    none = F.lit(0)
    return row(units, 0, "unit_id", none, none).unionByName(row(flows, 1, "src", F.col("dst"), F.col("w"))).unionByName(row(adjacency, 2, "a", F.col("b"), none))


def network_of(tab: pa.Table) -> kernel.Network:
    """The kernel's network, rows in a fixed order whatever the partitioning was."""
    kind, a, b, w = (tab.column(c).to_numpy() for c in ("kind", "a", "b", "w"))
    order = np.lexsort((b, a, kind))
    kind, a, b, w = kind[order], a[order], b[order], w[order]
    return kernel.Network(a[kind == 0], a[kind == 1], b[kind == 1], w[kind == 1], a[kind == 2], b[kind == 2])


def run(flows: DataFrame, units: DataFrame, adjacency: DataFrame, rep: str = "w", objective: str | Callable = "bm", stop: str = "full", b: int | None = None) -> DataFrame:
    """TRAJECTORY rows of every network. objective: bm, bm_dc, modularity (heap), map_equation, or a function from a kernel.Network to a kernel.Objective; b: groups to stop at with stop="fixed_b".

    Flows are sums of positive weights with both ends among the units. Networks without borders stay
    at their start; a network without flows merges in order of ids.
    """

    def solve(tab: pa.Table) -> pa.Table:
        name = tab.column("network_id")[0].as_py()
        net = network_of(tab)
        if callable(objective):
            path = kernel.greedy(net, objective(net), stop, b)
        elif objective == "modularity":
            path = kernel.greedy_modularity(net)
        elif objective == "map_equation":
            path = kernel.greedy_map_equation(net)
        else:
            path = kernel.greedy(net, kernel.BlockModel(rep, objective == "bm_dc"), stop, b)
        label = lambda k: int(net.units[k]) if k >= 0 else None
        columns = list(zip(*[(name, p[0], p[1], label(p[2]), label(p[3]), float(p[4]), float(p[5])) for p in path], strict=True))
        types = (pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64())
        return pa.table({f.split()[0]: pa.array(c, t) for f, c, t in zip(TRAJECTORY.split(", "), columns, types, strict=True)})

    return gathered(flows, units, adjacency).groupBy("network_id").applyInArrow(solve, TRAJECTORY)


def timed(flows: DataFrame, units: DataFrame, adjacency: DataFrame, rep: str = "w") -> DataFrame:
    """(network_id, n, e, seconds): wall time of the kernel alone for each network."""

    def solve(tab: pa.Table) -> pa.Table:
        net = network_of(tab)
        began = time.perf_counter()
        kernel.greedy(net, kernel.BlockModel(rep))
        spent = time.perf_counter() - began
        return pa.table({"network_id": [tab.column("network_id")[0].as_py()], "n": pa.array([net.n], pa.int64()), "e": pa.array([len(net.w)], pa.int64()), "seconds": [spent]})

    return gathered(flows, units, adjacency).groupBy("network_id").applyInArrow(solve, "network_id string, n long, e long, seconds double")


def best_step(trajectory: DataFrame) -> DataFrame:
    """(network_id, step, b, dl) of the shortest length visited; of equal ones the one with fewest groups."""
    least = F.min_by(F.struct("step", "b", "dl"), F.struct(F.round("dl", 9), F.col("b")))
    return trajectory.groupBy("network_id").agg(least.alias("m")).select("network_id", "m.step", "m.b", "m.dl")


def cut_path(trajectory: DataFrame, units: DataFrame, model: str, b: int | None = None) -> DataFrame:
    """PARTITION rows: the best partition of each path, or the one with b groups (or the fewest that it reached, if more).

    A unit's label is found by following the merges up to the chosen step; labels are the smallest
    unit of a group. Paths have at most N steps, so each network's merges are one task's work.
    """
    chosen = best_step(trajectory) if b is None else trajectory.filter(F.col("b") >= b).groupBy("network_id").agg(F.max("step").alias("step"))
    merges = trajectory.join(chosen.select("network_id", F.col("step").alias("_last")), "network_id").filter("step > 0 and step <= _last")
    rows = units.select("network_id", F.lit(0).alias("kind"), F.lit(0).alias("step"), F.col("unit_id").alias("p"), F.lit(0).alias("q")).unionByName(merges.select("network_id", F.lit(1).alias("kind"), "step", F.col("kept").alias("p"), F.col("absorbed").alias("q")))

    def follow(tab: pa.Table) -> pa.Table:
        kind, step, p, q = (tab.column(c).to_numpy() for c in ("kind", "step", "p", "q"))
        label = {int(u): int(u) for u in p[kind == 0]}
        up = {int(a): int(k) for _, k, a in sorted(zip(step[kind == 1], p[kind == 1], q[kind == 1], strict=True))}
        for u in label:
            at = u
            while at in up:
                at = up[at]
            label[u] = at
        ids = sorted(label)
        return pa.table({"network_id": pa.array([tab.column("network_id")[0].as_py()] * len(ids), pa.string()), "model": pa.array([model] * len(ids), pa.string()), "unit_id": pa.array(ids, pa.int32()), "label": pa.array([label[u] for u in ids], pa.int32())})

    return rows.groupBy("network_id").applyInArrow(follow, "network_id string, model string, unit_id int, label int")


def run_frames(flows: DataFrame, units: DataFrame, adjacency: DataFrame, rep: str = "w", steps: int | None = None) -> DataFrame:
    """The same path by DataFrame steps alone, one job for each merge: for tiny networks, as a check of the kernel."""
    model = "frame"
    flows, adjacency = cut(flows.select("network_id", "src", "dst", "w")), cut(adjacency.select("network_id", "a", "b"))
    part = cut(units.select("network_id", F.lit(model).alias("model"), "unit_id", F.col("unit_id").alias("label")))
    path = None
    step = 0
    while steps is None or step <= steps:
        score = dl.total(flows, part, rep).select("network_id", F.col("b").cast("int").alias("b"), "dl")
        gains = dl.merge_gains(flows, part, adjacency, rep)
        best = gains.groupBy("network_id").agg(F.min(F.struct(F.round("delta", 9).alias("delta"), "r", "s")).alias("m")).select("network_id", F.col("m.r").alias("r"), F.col("m.s").alias("s"))
        row = cut(score.select("network_id", F.lit(step).alias("step"), "b", "dl"))
        path = row if path is None else path.unionByName(row)
        best = cut(best)
        if best.isEmpty():
            break
        part = cut(part.join(best, "network_id", "left").select("network_id", "model", "unit_id", F.when(F.col("label") == F.col("s"), F.col("r")).otherwise(F.col("label")).alias("label")))
        step += 1
    return path


def run_rounds(flows: DataFrame, units: DataFrame, adjacency: DataFrame, rep: str = "w", most_rounds: int | None = None, stop: str = "first_increase", b: int | None = None, model: str = "rounds") -> tuple[DataFrame, DataFrame]:
    """(partition, history (network_id, round, b, dl)) of networks too large for one task: many merges a round.

    In a round every group nominates its best touching partner by gain, and mutual nominations merge
    together, the better half of them first. A network whose exact length does not fall keeps its
    partition and tries half as many next time, down to one; after a fall it tries twice as many.
    What follows when one merge does not help either is up to ``stop``: "first_increase" is done,
    "full" and "fixed_b" merge on, whatever the length does, until nothing touches or b groups are
    left; "full" returns the shortest partition visited, "fixed_b" the last. Rounds go on until no network
    is open; only a caller's ``most_rounds`` ends them before. Contiguity holds throughout; the order
    of merges is not the sequential one. The driver sees two numbers a round.
    """
    if stop not in ("full", "first_increase", "fixed_b") or (stop == "fixed_b" and b is None):
        raise ValueError("stop is full, first_increase, or fixed_b with b")
    least = b if stop == "fixed_b" else 1
    flows, adjacency = cut(flows.select("network_id", "src", "dst", "w")), cut(adjacency.select("network_id", "a", "b"))
    part = cut(units.select("network_id", F.lit(model).alias("model"), "unit_id", F.col("unit_id").alias("label"), F.col("unit_id").alias("best")))

    def score(p: DataFrame) -> DataFrame:
        """Networks without flows have the length of their partition alone."""
        found = dl.total(flows, p, rep).select("network_id", "dl")
        return dl.partition_bits(p).join(found, "network_id", "left").select("network_id", F.col("b").cast("int").alias("b"), F.coalesce("dl", "partition_bits").alias("dl"))

    state = score(part).withColumn("share", F.lit(1.0)).withColumn("least_dl", F.col("dl")).withColumn("up", F.lit(False))
    state = cut(state.withColumn("open", F.col("b") > least))
    history = state.select("network_id", F.lit(0).alias("round"), "b", "dl")
    k = 0
    while most_rounds is None or k < most_rounds:
        k += 1
        gains = dl.merge_gains(flows, part, adjacency, rep)
        both = gains.select("network_id", F.explode(F.array(F.struct(F.col("r").alias("x")), F.struct(F.col("s").alias("x")))).alias("e"), "r", "s", F.round("delta", 9).alias("delta"))
        choice = both.groupBy("network_id", "e.x").agg(F.min(F.struct("delta", "r", "s")).alias("m"))
        mutual = choice.groupBy("network_id", F.col("m.r").alias("r"), F.col("m.s").alias("s")).agg(F.count("*").alias("votes"), F.min("m.delta").alias("delta")).filter("votes = 2")
        rank = mutual.withColumn("rank", F.row_number().over(Window.partitionBy("network_id").orderBy("delta", "r", "s"))).withColumn("all", F.count("*").over(Window.partitionBy("network_id")))
        most = F.least(F.greatest(F.lit(1), F.floor(F.col("all") * F.col("share") / 2)), F.col("b") - least)
        batch = cut(rank.join(state.filter("open").select("network_id", "share", "b"), "network_id").filter(F.col("rank") <= most).select("network_id", F.col("s").alias("label"), "r", most.alias("many")))
        if batch.isEmpty():
            break
        new = cut(part.join(batch, ["network_id", "label"], "left").select("network_id", "model", "unit_id", F.coalesce("r", "label").alias("label")))
        many = batch.groupBy("network_id").agg(F.first("many").alias("many"))
        after = score(new).select("network_id", F.col("b").alias("b2"), F.col("dl").alias("dl2"))
        judged = state.join(after, "network_id").join(many, "network_id", "left")
        moved, better = F.col("many").isNotNull(), F.col("dl2") < F.col("dl")
        on = F.lit(stop != "first_increase") & (F.col("up") | (F.col("many") == 1))
        judged = judged.withColumn("took", moved & (better | on)).withColumn("shorter", F.col("took") & (F.round("dl2", 9) <= F.round("least_dl", 9)))
        up = F.when(F.col("shorter"), False).otherwise(F.col("up") | (F.col("took") & ~better))
        share = F.when(~moved, F.col("share")).when(up, 1.0).when(F.col("took"), F.least(F.lit(1.0), F.col("share") * 2)).otherwise(F.col("share") / 2)
        now = F.when(F.col("took"), F.col("b2")).otherwise(F.col("b"))
        still = F.col("open") & moved & (F.col("took") | (F.col("many") > 1)) & (now > least)
        state = cut(judged.select("network_id", now.alias("b"), F.when(F.col("took"), F.col("dl2")).otherwise(F.col("dl")).alias("dl"), share.alias("share"), F.when(F.col("shorter"), F.col("dl2")).otherwise(F.col("least_dl")).alias("least_dl"), up.alias("up"), still.alias("open"), "took", "shorter"))
        rows = part.withColumnRenamed("label", "before").join(new.select("network_id", "unit_id", "label"), ["network_id", "unit_id"]).join(state.select("network_id", "took", "shorter"), "network_id")
        part = cut(rows.select("network_id", "model", "unit_id", F.when(F.col("took"), F.col("label")).otherwise(F.col("before")).alias("label"), F.when(F.col("shorter"), F.col("label")).otherwise(F.col("best")).alias("best")))
        history = history.unionByName(state.filter("took").select("network_id", F.lit(k).alias("round"), "b", "dl"))
        if k % 50 == 0:
            history = cut(history)
        state = state.drop("took", "shorter")
    return part.select("network_id", "model", "unit_id", F.col("best" if stop == "full" else "label").alias("label")), history
