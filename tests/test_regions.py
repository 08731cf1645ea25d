import itertools
import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from flowregions.operators import adjacency as adj
from flowregions.operators import baselines, components, contiguity, dl, network, nulls, scores, similarity
from flowregions.plans import greedy, kernel, mcmc
from flowregions.sources import tables
from flowregions.sources import units as U
from flowregions.sources import workloads as W

SMALL, SF = "/root/testdata/sf0.001", "/root/testdata/sf0.01"


def brute(n, flows, label, rep):
    """Bits by whole-number binomials."""
    c = lambda a, b: math.log2(math.comb(a, b))
    m = lambda a, b: c(a + b - 1, b) if b else 0.0
    groups = sorted(set(label))
    size = {g: label.count(g) for g in groups}
    b = len(groups)
    e, w = len(flows), sum(f[2] for f in flows)
    bits = c(n - 1, b - 1) + math.log2(math.factorial(n)) - sum(math.log2(math.factorial(x)) for x in size.values())
    bits += m(b * b, w) + (0 if rep == "mg" else m(b * b, e))
    for r, s in itertools.product(groups, groups):
        some = [f for f in flows if label[f[0]] == r and label[f[1]] == s]
        if some:
            ww, ee, nn = sum(f[2] for f in some), len(some), size[r] * size[s]
            bits += m(nn, ww) if rep == "mg" else c(nn, ee) + c(ww - 1, ee - 1)
    return bits


FLOWS = [(0, 0, 3), (0, 1, 5), (1, 0, 2), (2, 3, 7), (3, 2, 1), (3, 3, 2), (1, 4, 1), (4, 5, 9), (5, 4, 2)]


@pytest.fixture(scope="module")
def tiny(spark):
    """Six units, three by two."""
    flows = spark.createDataFrame([("t", *f) for f in FLOWS], tables.FLOWS)
    units = U.grid(spark, 3, 2, "t")
    return flows, units, adj.from_cells(units)


def labels_frame(spark, labels, model="m"):
    return spark.createDataFrame([("t", model, u, g) for u, g in enumerate(labels)], tables.PARTITION)


@pytest.mark.parametrize("rep", ["mg", "w"])
def test_lengths_equal_whole_numbers(spark, tiny, rep):
    flows, _, _ = tiny
    cases = [[0] * 6, list(range(6)), [0, 0, 2, 2, 0, 0], [0, 1, 0, 1, 4, 4], [0, 0, 0, 3, 3, 3]]
    parts = None
    for k, labels in enumerate(cases):
        part = labels_frame(spark, labels, f"m{k}")
        parts = part if parts is None else parts.unionByName(part)
    got = {r.model: r.dl for r in dl.total(flows, parts, rep).collect()}
    for k, labels in enumerate(cases):
        assert got[f"m{k}"] == pytest.approx(brute(6, FLOWS, labels, rep), abs=1e-8)


def test_one_group_and_the_null(spark, tiny):
    flows, units, _ = tiny
    null = nulls.null_scores(flows, units).first().dl_null
    single = baselines.single(units)
    assert dl.total(flows, single, "mg").first().dl == pytest.approx(null, abs=1e-9)
    assert dl.total(flows, single, "w").first().dl <= null + 1e-9


@pytest.mark.parametrize("rep", ["mg", "w"])
def test_gains_are_differences_of_lengths(spark, tiny, rep):
    flows, units, borders = tiny
    labels = [0, 0, 2, 3, 3, 2]
    got = {(r.r, r.s): r.delta for r in dl.merge_gains(flows, labels_frame(spark, labels), borders, rep).collect()}
    model = kernel.BlockModel(rep)
    e, w = len(FLOWS), sum(f[2] for f in FLOWS)
    change = model.constant(6, 2, e, w) - model.constant(6, 3, e, w)
    assert got
    for (r, s), delta in got.items():
        merged = [r if g == s else g for g in labels]
        assert delta + change == pytest.approx(brute(6, FLOWS, merged, rep) - brute(6, FLOWS, labels, rep), abs=1e-7)


def kernel_net(n=6, flows=FLOWS, nx=3):
    border = [(i, i + 1) for i in range(n) if (i + 1) % nx] + [(i, i + nx) for i in range(n - nx)]
    f = np.array(flows)
    return kernel.Network(np.arange(n), f[:, 0], f[:, 1], f[:, 2], np.array([b[0] for b in border]), np.array([b[1] for b in border]))


@pytest.mark.parametrize("rep", ["mg", "w"])
def test_kernel_path_is_consistent_and_never_beats_all_contiguous_partitions(rep):
    path = kernel.greedy(kernel_net(), kernel.BlockModel(rep))
    assert [p[1] for p in path] == [6, 5, 4, 3, 2, 1]
    for p in path:
        labels = mcmc.labels_at(path, 6, p[0]).tolist()
        assert p[5] == pytest.approx(brute(6, FLOWS, labels, rep), abs=1e-7)
    best = min(brute(6, FLOWS, list(x), rep) for x in itertools.product(range(3), repeat=6))
    assert min(p[5] for p in path) >= best - 1e-9


@pytest.mark.parametrize("rep", ["mg", "w"])
def test_gain_for_all_pairs_at_random_states(rep):
    rng = np.random.default_rng(4)
    flows = [(int(a), int(b), int(w)) for a, b, w in {(x, y): (x, y, z) for x, y, z in zip(rng.integers(0, 12, 60), rng.integers(0, 12, 60), rng.integers(1, 9, 60), strict=True)}.values()]
    net = kernel_net(12, flows, 4)
    path = kernel.greedy(net, kernel.BlockModel(rep))
    for p in path:
        assert p[5] == pytest.approx(brute(12, flows, mcmc.labels_at(path, 12, p[0]).tolist(), rep), abs=1e-6)


#: Golden values: workload, scale, form, best length, groups.
GOLDEN = [("nation", SMALL, "w", 1078.2434, 4), ("nation", SMALL, "mg", 997.9268, 5), ("nation", SF, "w", 3076.4897, 5), ("nation", SF, "mg", 3031.1426, 5), ("tract", SMALL, "w", 3120.3022, 11), ("tract", SF, "w", 19221.5943, 12), ("tract", SF, "mg", 18288.1263, 19)]


@pytest.mark.parametrize("kind,sf,rep,best,b", GOLDEN)
def test_golden_lengths(spark, kind, sf, rep, best, b):
    flows = (W.planted if kind == "nation" else W.tracts)(spark, sf)
    units = U.nations(spark, "planted") if kind == "nation" else U.tracts(spark)
    row = greedy.best_step(greedy.run(flows, units, adj.from_cells(units), rep)).first()
    assert row.b == b and row.dl == pytest.approx(best, abs=1e-3)


def test_planted_regions_are_found_and_contiguous(spark):
    flows, units = W.planted(spark, SF), U.nations(spark, "planted")
    borders = adj.from_cells(units)
    part = greedy.cut_path(greedy.run(flows, units, borders), units, "ga")
    assert similarity.ami(part, baselines.admin(units)).first().ami == pytest.approx(1)
    row = contiguity.measures(part, borders).first()
    assert row.cvm == pytest.approx(0, abs=1e-12) and row.broken == 0
    again = greedy.cut_path(greedy.run(flows.repartition(7), units.repartition(3), borders.repartition(5)), units, "ga")
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, part.collect()))


def test_no_structure_gives_one_region(spark):
    units = U.nations(spark, "trade")
    assert greedy.best_step(greedy.run(W.trade(spark, SF), units, adj.from_cells(units))).first().b == 1


def test_stops_and_cuts(spark, tiny):
    flows, units, borders = tiny
    full = greedy.run(flows, units, borders).collect()
    fixed = greedy.run(flows, units, borders, stop="fixed_b", b=3).collect()
    assert [r.b for r in sorted(fixed, key=lambda r: r.step)] == [6, 5, 4, 3]
    part = greedy.cut_path(greedy.run(flows, units, borders), units, "ga", 3)
    assert part.select("label").distinct().count() == 3 and len(full) == 6


def test_frames_equal_the_kernel(spark, tiny):
    flows, units, borders = tiny
    want = {r.step: r.dl for r in greedy.run(flows, units, borders, "w").collect()}
    got = {r.step: r.dl for r in greedy.run_frames(flows, units, borders, "w", steps=2).collect()}
    for step, value in got.items():
        assert value == pytest.approx(want[step], abs=1e-7)


def test_rounds_stay_contiguous_and_fall(spark, tiny):
    flows, units, borders = tiny
    part, history = greedy.run_rounds(flows, units, borders, "w", most_rounds=4)
    values = [r.dl for r in history.orderBy("round").collect()]
    assert values == sorted(values, reverse=True)
    assert contiguity.measures(part, borders).first().broken == 0


def test_rounds_end_when_nothing_touches(spark):
    units = U.grid(spark, 14, 1, "t")
    flows = spark.createDataFrame([], tables.FLOWS)  # one mutual pair a round
    part, history = greedy.run_rounds(flows, units, adj.from_cells(units), stop="full")
    assert sorted(r.b for r in history.collect()) == list(range(1, 15))
    assert {r.label for r in part.collect()} == {0} and part.count() == 14


def test_rounds_honour_stop_and_b_and_refuse_the_rest(spark, tiny):
    from flowregions import model

    flows, units, borders = tiny
    net = model.Network(units, flows, borders)
    fixed = model.Regionalizer(stop="fixed_b", b=4, impl="rounds").fit(net)
    assert fixed.partition.select("label").distinct().count() == 4
    for wrong in ({"objective": "modularity", "impl": "rounds"}, {"impl": "auto"}):
        with pytest.raises(ValueError):
            model.Regionalizer(**wrong).fit(net)
    own = model.Regionalizer(objective=lambda n: kernel.modularity_objective(float(n.w.sum()))).fit(net)
    heap = model.Regionalizer(objective="modularity").fit(net)
    assert own.trajectory.agg(F.min("dl")).first()[0] == pytest.approx(heap.trajectory.agg(F.min("dl")).first()[0])


def test_objectives_with_costly_empty_blocks_are_refused():
    with pytest.raises(ValueError):
        kernel.greedy(kernel_net(), kernel.Objective(pair=lambda nn, e, w: np.ones(np.shape(e))))


@pytest.mark.parametrize("make", [lambda net: kernel.BlockModel("w"), lambda net: kernel.BlockModel("mg", True), lambda net: kernel.poisson_objective(), lambda net: kernel.modularity_objective(float(net.w.sum()))])
def test_totals_are_constant_plus_groups_plus_pairs(make):
    """Every step of a greedy path, from the blocks of its labels alone."""
    net = kernel_net()
    model = make(net)
    path = kernel.greedy(net, model)
    for p in path:
        label = np.unique(mcmc.labels_at(path, net.n, p[0]), return_inverse=True)[1].ravel()
        b = label.max() + 1
        e, w = (np.zeros((b, b), dtype=np.int64) for _ in range(2))
        np.add.at(e, (label[net.src], label[net.dst]), net.e)
        np.add.at(w, (label[net.src], label[net.dst]), net.w)
        ends = w if model.ends == "w" else e
        size = np.bincount(label)
        one = net.w if model.ends == "w" else net.e
        fixed = model.fixed(net.e, net.w, *(np.bincount(x, weights=one, minlength=net.n).astype(np.int64) for x in (net.src, net.dst)))
        some = e > 0
        want = model.constant(net.n, b, int(e.sum()), int(w.sum())) + model.group(size, ends.sum(1), ends.sum(0), np.diag(ends)).sum() + model.pair((size[:, None] * size)[some], e[some], w[some]).sum() + fixed
        assert p[5] == pytest.approx(float(want), abs=1e-9)


def test_disconnected_borders_keep_components(spark):
    flows = spark.createDataFrame([("t", 0, 1, 5), ("t", 2, 3, 5)], tables.FLOWS)
    units = U.grid(spark, 4, 1, "t")
    borders = spark.createDataFrame([("t", 0, 1, 1.0), ("t", 2, 3, 1.0)], tables.ADJACENCY)
    assert greedy.run(flows, units, borders).agg(F.min("b")).first()[0] == 2
    assert components.number(borders, units).first().components == 2


def test_annealed_lengths_are_true_and_not_above_their_start(spark, tiny):
    flows, units, borders = tiny
    fits = mcmc.anneal(flows, units, borders, ("bm", "bm_n", "bm_r"), ("mg", "w")).collect()
    by = {}
    for r in fits:
        by.setdefault((r.model, r.rep), []).append(r)
    assert len(by) == 6
    for (model, rep), rows in by.items():
        assert rows[0].dl <= rows[0].start + 1e-9
        if model == "bm":
            labels = [r.label for r in sorted(rows, key=lambda r: r.unit_id)]
            assert rows[0].dl == pytest.approx(brute(6, FLOWS, labels, rep), abs=1e-6)
    for rep in ("mg", "w"):
        assert by["bm_n", rep][0].dl <= by["bm", rep][0].dl + 1e-9


def test_nested_with_one_level_is_flat_and_switches_keep_the_rest():
    rng = np.random.default_rng(1)
    e = rng.integers(0, 5, (2, 2))
    w = e * 3
    assert mcmc.nested_bits(e, w, "w", False)[0] == pytest.approx(mcmc.matrix_bits(e, w, "w", False))
    e = np.diag([50] * 9)
    assert mcmc.nested_bits(e, e, "mg", False)[0] <= mcmc.matrix_bits(e, e, "mg", False)


@pytest.mark.parametrize("rep", ["mg", "w"])
@pytest.mark.parametrize("variant", mcmc.VARIANTS)
def test_priced_moves_are_differences_of_lengths(variant, rep):
    """Random moves, also into and out of empty groups, against the chain built anew; nested ones under the hierarchy as it stands."""
    rng = np.random.default_rng(4)
    src, dst = rng.integers(0, 16, 90), rng.integers(0, 16, 90)
    pairs, w = np.unique(src * 16 + dst, return_counts=True)
    net = kernel.Network(np.arange(16), pairs // 16, pairs % 16, w, np.arange(15), np.arange(1, 16))
    chain = mcmc.Chain(net, variant, rep, rng.integers(0, 7, 16))
    if chain.ranked:
        chain.rank()
    if chain.nested:
        chain.grow()
    price = lambda c: c.below() + (c.tree.now if c.tree is not None else c.matrix(len(c.active), c.ways))
    for _ in range(120):
        i = int(rng.integers(16))
        s = chain.active[int(rng.integers(len(chain.active)))] if rng.random() < 0.8 or chain.size[chain.label[i]] == 1 else chain.empty()
        if s == chain.label[i]:
            continue
        before = price(chain)
        bits, what = chain.change(i, s)
        chain.move(i, s, what)
        assert price(chain) - before == pytest.approx(bits, abs=1e-7)
        again = mcmc.Chain(net, variant, rep, chain.labels())
        assert again.below() == pytest.approx(chain.below(), abs=1e-7) and again.ways == chain.ways


def test_annealed_models_reach_the_best_of_all_partitions():
    """Five units: every labelling, for the flat variants that need no ranking."""
    rng = np.random.default_rng(2)
    pairs, w = np.unique(rng.integers(0, 25, 60), return_counts=True)
    net = kernel.Network(np.arange(5), pairs // 5, pairs % 5, w, np.arange(4), np.arange(1, 5))
    for variant in ("bm", "bm_dc"):
        for rep in ("mg", "w"):
            best = min(mcmc.Chain(net, variant, rep, np.array(label)).length() for label in itertools.product(range(5), repeat=5))
            merges = mcmc.merge_paths(net, rep)
            assert min(mcmc.fit(net, variant, rep, mcmc.generator(k), merges)[0].length() for k in range(4)) == pytest.approx(best)


def test_effective_components_by_hand(spark):
    rows = [("t", "m", 0, 0, 2), ("t", "m", 0, 1, 3), ("t", "m", 5, 5, 3), ("t", "m", 5, 6, 1), ("t", "m", 9, 9, 2), ("t", "m", 9, 10, 2)]
    got = {r.label: r.c_eff for r in contiguity.effective_components(spark.createDataFrame(rows, "network_id string, model string, label int, comp int, n_rc long")).collect()}
    assert got[0] == pytest.approx(1.960, abs=1e-3) and got[5] == pytest.approx(1.755, abs=1e-3) and got[9] == pytest.approx(2)


def test_checkerboard_is_the_extreme(spark):
    units = U.nations(spark)
    row = contiguity.measures(baselines.by_rule(units, "(x + y) % 2", "board"), adj.from_cells(units)).first()
    assert row.cvm == pytest.approx(25 / 2 - 1)


def test_similarity_limits(spark):
    units = U.nations(spark).withColumn("area", F.lit(1.0))
    rows, cols = baselines.by_rule(units, "y", "rows"), baselines.by_rule(units, "x", "cols")
    assert similarity.spatial_nmi(rows, cols, units).first().snmi == pytest.approx(0, abs=1e-12)
    assert similarity.spatial_nmi(rows, rows, units).first().snmi == pytest.approx(1)
    third = baselines.by_rule(units, "unit_id % 3", "third")
    assert similarity.spatial_nmi(rows, third, units).first().snmi == pytest.approx(similarity.nmi(rows, third).first().nmi)


def test_coarsening_keeps_the_weight(spark):
    fine, units = W.tracts(spark, SMALL), U.tracts(spark)
    coarse = network.coarsen(fine, units)
    assert coarse.agg(F.sum("w")).first()[0] == fine.agg(F.sum("w")).first()[0]
    want = {(r.src, r.dst): r.w for r in W.planted(spark, SMALL).collect()}
    assert {(r.src, r.dst): r.w for r in coarse.collect()} == want


def test_corner_contact_is_no_border(spark):
    units = U.grid(spark, 2, 2, "t")
    pairs = {(r.a, r.b) for r in adj.from_segments(adj.cell_segments(units)).collect()}
    assert pairs == {(0, 1), (2, 3), (0, 2), (1, 3)}


def test_best_model_prefers_the_simpler_of_equals(spark):
    rows = spark.createDataFrame([("n", "bm_n", "w", 3, 10.0), ("n", "bm", "w", 3, 10.0), ("n", "bm_dc", "w", 3, 12.0)], "network_id string, model string, rep string, b int, dl double")
    assert scores.best_model(rows).first().model == "bm"


def test_flow_plans_stay_in_the_jvm(spark):
    flows = W.planted(spark, SMALL)
    plan = dl.total(flows, baselines.admin(U.nations(spark, "planted")), "w")._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Broadcast" in plan
    assert "l_extendedprice" not in flows._jdf.queryExecution().executedPlan().toString()


def test_regionalize_in_sql(spark, tiny):
    from flowregions import sqlapi

    sqlapi.register(spark)
    flows, units, borders = tiny
    greedy.gathered(flows, units, borders).createOrReplaceTempView("tiny_net")
    got = spark.sql("select * from regionalize(table(tiny_net) partition by network_id)").collect()
    want = greedy.best_step(greedy.run(flows, units, borders, "w")).first()
    assert len(got) == 6 and got[0].b == want.b and got[0].dl == pytest.approx(want.dl)


def test_user_objects(spark, tiny):
    from flowregions.model import Network, Panel, Regionalizer

    flows, units, borders = tiny
    net = Network(units, flows, borders)
    model = Regionalizer(rep="mg").fit(net)
    assert model.score().first().eta > 0 and model.contiguity().first().broken == 0
    assert model.cut(2).select("label").distinct().count() == 2
    assert Panel(net).run(("bm",), ("w",)).count() == 2


def test_readers_and_sinks(spark, tmp_path):
    flows = spark.createDataFrame([("a", 1, 2, 3), ("b", 2, 1, 4)], tables.FLOWS)
    from flowregions.operators import sinks

    for fmt in ("csv", "json", "orc", "parquet"):
        writer = flows.write.option("header", True)
        writer.format(fmt).save(str(tmp_path / fmt))
        assert sorted(map(tuple, tables.read_flows(spark, str(tmp_path / fmt), fmt).collect())) == [("a", 1, 2, 3), ("b", 2, 1, 4)]
    sinks.write(flows.withColumn("model", F.lit("x")), str(tmp_path / "out"))
    assert spark.read.parquet(str(tmp_path / "out")).count() == 2
    assert tables.invalid_flows(spark.createDataFrame([("a", 1, None, 3), ("a", 1, 2, 0)], tables.FLOWS)).count() == 2


def test_planted_source(spark):
    flows = tables.planted(spark, 20, 4, 30, 3)
    units = U.grid(spark, 20, 1, "planted")
    part = greedy.cut_path(greedy.run(flows, units, adj.from_cells(units), "mg"), units, "ga")
    truth = baselines.by_rule(units, "floor(unit_id / 5)", "truth")
    assert similarity.ami(part, truth).first().ami > 0.9
