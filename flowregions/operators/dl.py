"""Description lengths of flows given a partition, term by term, from sparse block matrices.

One plan: flows meet their labels (two joins), blocks are summed (one shuffle), bits are expressions
on at most min(E, B^2) rows, and three small sums meet in one row for each network. No Python.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from flowregions.functions.bits import lchoose, lcompositions, lfact, lmulti
from flowregions.operators.network import small
from flowregions.plans.checkpoints import cut

KEYS = ("network_id", "model")


def groups(partition: DataFrame) -> DataFrame:
    """(network_id, model, label, n): sizes of the groups."""
    return partition.groupBy(*KEYS, "label").agg(F.count("*").alias("n"))


def labelled(flows: DataFrame, partition: DataFrame) -> DataFrame:
    """Flows with the labels of both ends: (network_id, model, src, dst, w, r, s)."""
    side = small(partition)
    first = flows.join(side.select("network_id", "model", F.col("unit_id").alias("src"), F.col("label").alias("r")), ["network_id", "src"])
    return first.join(side.select("network_id", "model", F.col("unit_id").alias("dst"), F.col("label").alias("s")), ["network_id", "model", "dst"])


def blocks(flows: DataFrame, partition: DataFrame) -> DataFrame:
    """(network_id, model, r, s, e, w, n_r, n_s): the mixing matrices where they are not zero."""
    sums = labelled(flows, partition).groupBy(*KEYS, "r", "s").agg(F.count("*").alias("e"), F.sum("w").alias("w"))
    size = groups(partition)
    return sums.join(size.select(*KEYS, F.col("label").alias("r"), F.col("n").alias("n_r")), [*KEYS, "r"]).join(size.select(*KEYS, F.col("label").alias("s"), F.col("n").alias("n_s")), [*KEYS, "s"]).select(*KEYS, "r", "s", "e", "w", "n_r", "n_s")


def partition_bits(partition: DataFrame) -> DataFrame:
    """(network_id, model, n, b, partition_bits): group sizes, then the assignment."""
    rows = groups(partition).groupBy(*KEYS).agg(F.sum("n").alias("n"), F.count("*").alias("b"), F.sum(lfact("n")).alias("inside"))
    bits = lchoose("n - 1", "b - 1") + lfact("n") - F.col("inside")
    return rows.select(*KEYS, "n", "b", bits.alias("partition_bits"))


#: Pairs of units of a block, as SQL text.
PAIRS = "CAST(n_r AS DOUBLE) * n_s"


def block_bits(blocks_: DataFrame, degree_corrected: bool = False) -> DataFrame:
    """(network_id, model, e, w, mg_bits, simple_bits, weight_bits): sums over the blocks."""
    aggs = [F.sum("e").alias("e"), F.sum("w").alias("w"), F.sum(lcompositions("w", "e")).alias("weight_bits")]
    if degree_corrected:
        aggs += [(-F.sum(lfact("w"))).alias("mg_bits"), (-F.sum(lfact("e"))).alias("simple_bits")]
    else:
        aggs += [F.sum(lmulti(PAIRS, "w")).alias("mg_bits"), F.sum(lchoose(PAIRS, "e")).alias("simple_bits")]
    return blocks_.groupBy(*KEYS).agg(*aggs)


def degree_bits(flows: DataFrame, partition: DataFrame, rep: str) -> DataFrame:
    """(network_id, model, degree_bits): what the degree-corrected models add to block_bits: arrangements of edge ends, priors of the degrees."""
    one = F.col("w") if rep == "mg" else F.lit(1)
    rows = labelled(flows, partition).withColumn("one", one)
    parts = rows.groupBy(*KEYS).agg(F.sum(lfact("one")).alias("bits"))
    for end, label in (("src", "r"), ("dst", "s")):
        unit = rows.groupBy(*KEYS, end, label).agg(F.sum("one").alias("k"))
        inside = unit.groupBy(*KEYS, F.col(label).alias("label")).agg(F.sum("k").alias("k"), F.sum(lfact("k")).alias("own")).join(groups(partition), [*KEYS, "label"])
        more = inside.groupBy(*KEYS).agg(F.sum(lfact("k") + lmulti("n", "k") - F.col("own")).alias("more"))
        parts = parts.join(more, list(KEYS)).select(*KEYS, (F.col("bits") + F.col("more")).alias("bits"))
    return parts.withColumnRenamed("bits", "degree_bits")


def ranked_matrix_bits(blocks_: DataFrame, b: DataFrame, rep: str) -> DataFrame:
    """(network_id, model, matrix_bits): edges up, down and along a ranking of the groups (by label), each spread over its own pairs of groups."""
    def spread(x: str) -> Column:
        up, down, flat = (f"{x}_{k}" for k in ("up", "down", "flat"))
        half = "b * (b - 1) / 2"
        some = lambda slots, n: F.when(F.expr(f"{slots} > 0"), lmulti(slots, n)).otherwise(0.0)
        return lmulti(3, f"{up} + {down} + {flat}") + some(half, up) + some(half, down) + some("b", flat)

    sums = [F.coalesce(F.sum(F.when(cond, F.col(x))), F.lit(0)).alias(f"{x}_{k}") for x in ("e", "w") for k, cond in (("up", F.col("r") < F.col("s")), ("down", F.col("r") > F.col("s")), ("flat", F.col("r") == F.col("s")))]
    rows = blocks_.groupBy(*KEYS).agg(*sums).join(b.select(*KEYS, "b"), list(KEYS))
    return rows.select(*KEYS, (spread("w") if rep == "mg" else spread("e") + spread("w")).alias("matrix_bits"))


def total(flows: DataFrame, partition: DataFrame, rep: str = "w", degree_corrected: bool = False, ranked: bool = False, cells: DataFrame | None = None) -> DataFrame:
    """(network_id, model, rep, n, b, e, w, partition_bits, matrix_bits, placement_bits, weight_bits, dl) of each partition.

    A partition must label every unit of its network; flows with an unlabelled end are left out. A network
    without flows has the length of its partition alone. cells: the partition's blocks, where they are known.
    """
    cells = blocks(flows, partition) if cells is None else cells
    part, inside = partition_bits(partition), block_bits(cells, degree_corrected)
    rows = part.join(inside, list(KEYS), "left").na.fill(0, ["e", "w", "mg_bits", "simple_bits", "weight_bits"])
    square = "CAST(b AS DOUBLE) * b"
    if ranked:
        rows = rows.join(ranked_matrix_bits(cells, part, rep), list(KEYS), "left").na.fill(0, ["matrix_bits"])
    else:
        matrix = lmulti(square, "w") if rep == "mg" else lmulti(square, "e") + lmulti(square, "w")
        rows = rows.withColumn("matrix_bits", matrix)
    placement = F.col("mg_bits") if rep == "mg" else F.col("simple_bits")
    if degree_corrected:
        rows = rows.join(degree_bits(flows, partition, rep), list(KEYS), "left").na.fill(0, ["degree_bits"])
        placement = placement + F.col("degree_bits")
    weight = F.lit(0.0) if rep == "mg" else F.col("weight_bits")
    rows = rows.withColumn("placement_bits", placement).withColumn("weight_bits", weight).withColumn("dl", F.col("partition_bits") + F.col("matrix_bits") + F.col("placement_bits") + F.col("weight_bits"))
    return rows.select(*KEYS, F.lit(rep).alias("rep"), "n", "b", "e", "w", "partition_bits", "matrix_bits", "placement_bits", "weight_bits", "dl")


def nested_total(flows: DataFrame, hierarchy: DataFrame, rep: str = "w", degree_corrected: bool = False, ranked: bool = False) -> DataFrame:
    """(network_id, model, dl) of a hierarchy (network_id, model, level, node, label), level 0 the units', the last one of a single group.

    The matrix of each level is a multigraph that the next level describes; ranked: the last matrix, the one below the
    single group, is priced along the order of its nodes. Hierarchies of one table may differ in depth.
    """
    base = hierarchy.filter("level = 0").select("network_id", "model", F.col("node").alias("unit_id"), "label")
    known = cut(blocks(flows, base))  # every level is summed from these
    bits = total(flows, base, rep, degree_corrected, cells=known).select(*KEYS, (F.col("partition_bits") + F.col("placement_bits") + F.col("weight_bits")).alias("bits"))
    depth = hierarchy.groupBy(*KEYS).agg(F.max("level").alias("depth"))
    deepest = hierarchy.agg(F.max("level")).first()[0] or 0
    cells = known.select(*KEYS, F.col("r").alias("src"), F.col("s").alias("dst"), "e", "w")
    for level in range(1, deepest + 1):
        part = hierarchy.filter(F.col("level") == level).select("network_id", "model", F.col("node").alias("unit_id"), "label")
        up = lambda end, to: part.select("network_id", "model", F.col("unit_id").alias(end), F.col("label").alias(to))  # noqa: B023,E731
        above = cells.join(up("src", "r"), [*KEYS, "src"]).join(up("dst", "s"), [*KEYS, "dst"]).groupBy(*KEYS, "r", "s").agg(F.sum("e").alias("e"), F.sum("w").alias("w"))
        size = groups(part)
        sized = above.join(size.select(*KEYS, F.col("label").alias("r"), F.col("n").alias("n_r")), [*KEYS, "r"]).join(size.select(*KEYS, F.col("label").alias("s"), F.col("n").alias("n_s")), [*KEYS, "s"])
        cost = lmulti(PAIRS, "w") if rep == "mg" else lmulti(PAIRS, "e") + lmulti(PAIRS, "w")
        here = sized.groupBy(*KEYS).agg(F.sum(cost).alias("matrix")).join(partition_bits(part), list(KEYS))
        if ranked:
            order = ranked_matrix_bits(cells.withColumnsRenamed({"src": "r", "dst": "s"}), here.select(*KEYS, F.col("n").alias("b")), rep).withColumnRenamed("matrix_bits", "order")
            here = here.join(depth, list(KEYS)).join(order, list(KEYS), "left").withColumn("matrix", F.when(F.col("depth") == level, F.col("order")).otherwise(F.col("matrix")))
        bits = bits.join(here.select(*KEYS, (F.col("matrix") + F.col("partition_bits")).alias("more")), list(KEYS), "left").select(*KEYS, (F.col("bits") + F.coalesce("more", F.lit(0.0))).alias("bits"))
        cells = above.select(*KEYS, F.col("r").alias("src"), F.col("s").alias("dst"), "e", "w")
    return bits.withColumnRenamed("bits", "dl")


def objective_total(flows: DataFrame, partition: DataFrame, constant: Callable, group: Callable | None = None, pair: Callable | None = None) -> DataFrame:
    """(network_id, model, b, total) of any constant(n, b, e, w) + sum of group(n, out, into, own) + sum of pair(nn, e, w), given as functions of columns.

    out, into and own count weight. The twin of kernel.Objective as one plan.
    """
    cells = blocks(flows, partition)
    rows = partition_bits(partition).select(*KEYS, "n", "b").join(cells.groupBy(*KEYS).agg(F.sum("e").alias("e"), F.sum("w").alias("w"), (F.sum(pair(F.expr(PAIRS), F.col("e"), F.col("w"))) if pair else F.lit(0.0)).alias("pairs")), list(KEYS), "left").na.fill(0)
    value = constant(F.col("n"), F.col("b"), F.col("e"), F.col("w")) + F.col("pairs")
    if group:
        ends = cells.groupBy(*KEYS, F.col("r").alias("label")).agg(F.sum("w").alias("out"), F.sum(F.when(F.col("r") == F.col("s"), F.col("w")).otherwise(0)).alias("own")).join(cells.groupBy(*KEYS, F.col("s").alias("label")).agg(F.sum("w").alias("into")), [*KEYS, "label"], "full_outer")
        each = groups(partition).withColumnRenamed("n", "size").join(ends, [*KEYS, "label"], "left").na.fill(0).join(rows.select(*KEYS, "w"), list(KEYS))
        rows = rows.join(each.groupBy(*KEYS).agg(F.sum(group(F.col("size"), F.col("out"), F.col("into"), F.col("own"), F.col("w"))).alias("groups")), list(KEYS))
        value = value + F.col("groups")
    return rows.select(*KEYS, "b", value.alias("total"))


def per_node(scores: DataFrame) -> DataFrame:
    """Adds ``dl_per_node``."""
    return scores.withColumn("dl_per_node", F.col("dl") / F.col("n"))


def log2_odds(scores: DataFrame, a: str, b: str) -> DataFrame:
    """(network_id, log2_odds): bits by which model a is shorter than model b; the posterior odds of a are 2 to that power, kept as exponent."""
    of = lambda m, name: scores.filter(F.col("model") == m).select("network_id", F.col("dl").alias(name))
    return of(a, "dl_a").join(of(b, "dl_b"), "network_id").select("network_id", (F.col("dl_b") - F.col("dl_a")).alias("log2_odds"))


def modularity(flows: DataFrame, partition: DataFrame) -> DataFrame:
    """(network_id, model, modularity): directed, by weight."""
    cells = blocks(flows, partition)
    all_ = cells.groupBy(*KEYS).agg(F.sum("w").alias("all"))
    out = cells.groupBy(*KEYS, F.col("r").alias("label")).agg(F.sum("w").alias("k_out"), F.sum(F.when(F.col("r") == F.col("s"), F.col("w")).otherwise(0)).alias("own"))
    into = cells.groupBy(*KEYS, F.col("s").alias("label")).agg(F.sum("w").alias("k_in"))
    rows = out.join(into, [*KEYS, "label"], "left").join(all_, list(KEYS))
    term = F.col("own") / F.col("all") - F.col("k_out").cast("double") * F.coalesce("k_in", F.lit(0)) / (F.col("all").cast("double") * F.col("all"))
    return rows.groupBy(*KEYS).agg(F.sum(term).alias("modularity"))


def merge_gains(flows: DataFrame, partition: DataFrame, adjacency: DataFrame, rep: str = "w") -> DataFrame:
    """(network_id, model, r, s, delta): the change of the group and block terms for every pair of touching groups.

    Blocks meet the candidates at either end; neighbours other than r and s count once.
    """
    cells = blocks(flows, partition)
    size = groups(partition)
    side = partition.select("network_id", "model", F.col("unit_id"), "label")
    touch = adjacency.join(side.select("network_id", "model", F.col("unit_id").alias("a"), F.col("label").alias("la")), ["network_id", "a"]).join(side.select("network_id", "model", F.col("unit_id").alias("b"), F.col("label").alias("lb")), ["network_id", "model", "b"]).filter("la != lb")
    pairs = touch.select(*KEYS, F.least("la", "lb").alias("r"), F.greatest("la", "lb").alias("s")).distinct()
    pairs = pairs.join(size.select(*KEYS, F.col("label").alias("r"), F.col("n").alias("nr")), [*KEYS, "r"]).join(size.select(*KEYS, F.col("label").alias("s"), F.col("n").alias("ns")), [*KEYS, "s"])
    cost = (lambda nn, e, w: lmulti(nn, w)) if rep == "mg" else (lambda nn, e, w: lchoose(nn, e) + lcompositions(w, e))  # noqa: ARG005
    mine = cells.withColumn("cost", cost(PAIRS, "e", "w"))
    # every block with an end in r or s, seen from the candidate: its other end u, or r itself when it lies within
    ends = F.explode(F.array_distinct(F.array("r", "s")))
    seen = mine.withColumn("end", ends)
    hit = pairs.select(*KEYS, "r", "s", "nr", "ns", F.explode(F.array("r", "s")).alias("end")).withColumnsRenamed({"r": "cr", "s": "cs"})
    rows = hit.join(seen, [*KEYS, "end"])
    inside = lambda c: (F.col(c) == F.col("cr")) | (F.col(c) == F.col("cs"))
    rows = rows.withColumn("way", F.when(inside("r") & inside("s"), 0).when(inside("r"), 1).otherwise(2))
    rows = rows.filter(~((F.col("way") == 0) & (F.col("r") != F.col("s")) & (F.col("end") == F.col("s"))))  # a block between r and s is met from both ends
    u = F.when(F.col("way") == 1, F.col("s")).when(F.col("way") == 2, F.col("r")).otherwise(F.lit(-1))
    nu = F.when(F.col("way") == 1, F.col("n_s")).when(F.col("way") == 2, F.col("n_r")).otherwise(F.col("nr") + F.col("ns"))
    merged = rows.groupBy(*KEYS, "cr", "cs", "nr", "ns", "way", u.alias("u"), nu.alias("nu")).agg(F.sum("e").alias("e"), F.sum("w").alias("w"), F.sum("cost").alias("old"))
    change = cost("CAST(nr + ns AS DOUBLE) * nu", "e", "w") - F.col("old")
    changes = merged.withColumn("change", change).groupBy(*KEYS, F.col("cr").alias("r"), F.col("cs").alias("s")).agg(F.sum("change").alias("change"))
    own = lfact("nr") + lfact("ns") - lfact("nr + ns")
    return pairs.join(changes, [*KEYS, "r", "s"], "left").select(*KEYS, "r", "s", (own + F.coalesce("change", F.lit(0.0))).alias("delta"))
