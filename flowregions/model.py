"""The end user's objects: Regionalizer, RegionModel, Panel."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from flowregions.operators import contiguity, dl, nulls, scores, similarity
from flowregions.plans import greedy, mcmc
from flowregions.plans.checkpoints import cut


@dataclass
class Network:
    """Units, flows and borders of one or many networks."""

    units: DataFrame
    flows: DataFrame
    adjacency: DataFrame


@dataclass
class RegionModel:
    network: Network
    partition: DataFrame
    trajectory: DataFrame | None
    rep: str
    name: str

    def cut(self, b: int) -> DataFrame:
        """The partition with b groups, from the merges already made."""
        if self.trajectory is None:
            raise ValueError("merging in rounds keeps no single merges; fit with stop='fixed_b' and b")
        return greedy.cut_path(self.trajectory, self.network.units, f"{self.name}_{b}", b)

    def score(self, flows: DataFrame | None = None) -> DataFrame:
        found = dl.total(flows if flows is not None else self.network.flows, self.partition, self.rep)
        return scores.compression_ratio(found, nulls.null_scores(self.network.flows, self.network.units))

    def contiguity(self) -> DataFrame:
        return contiguity.measures(self.partition, self.network.adjacency)

    def compare(self, other: DataFrame) -> DataFrame:
        ami = similarity.ami(self.partition, other)
        return ami.join(similarity.spatial_nmi(self.partition, other, self.network.units), ["network_id", "p_model", "q_model"])


@dataclass
class Regionalizer:
    """rep: w or mg; objective: bm, bm_dc, modularity, map_equation, or a function from a kernel.Network to a kernel.Objective;
    stop: full, first_increase, fixed_b; impl: kernel (one task a network) or rounds (joins, for a network beyond a task's memory).

    Which one runs is the caller's choice at any size, as rounds merge in another order. Rounds honour stop and b and
    serve the objective bm alone; others are refused.
    """

    rep: str = "w"
    objective: str | Callable = "bm"
    stop: str = "full"
    b: int | None = None
    impl: str = "kernel"

    def fit(self, network: Network) -> RegionModel:
        name = "ga_own" if callable(self.objective) else f"ga_{self.objective}"
        if self.impl not in ("kernel", "rounds"):
            raise ValueError("impl is kernel or rounds")
        if self.impl == "rounds" and self.objective != "bm":
            raise ValueError(f"merging in rounds has no objective {self.objective}; use impl='kernel'")
        if self.impl == "rounds":
            return RegionModel(network, self._by_rounds(network, name), None, self.rep, name)
        return RegionModel(network, *self._by_kernel(network, name), self.rep, name)

    def _by_kernel(self, network: Network, name: str) -> tuple[DataFrame, DataFrame]:
        trajectory = cut(greedy.run(network.flows, network.units, network.adjacency, self.rep, self.objective, self.stop, self.b))
        last = self.b if self.stop == "fixed_b" else None
        return greedy.cut_path(trajectory, network.units, name, last), trajectory

    def _by_rounds(self, network: Network, name: str) -> DataFrame:
        return greedy.run_rounds(network.flows, network.units, network.adjacency, self.rep, stop=self.stop, b=self.b, model=name)[0]


@dataclass
class Panel:
    network: Network

    def run(self, variants: tuple[str, ...] = mcmc.VARIANTS, reps: tuple[str, ...] = ("mg", "w"), chains: int = 1, seed: int = 1) -> DataFrame:
        """(network_id, model, rep, n, b, dl) of all block models and of the greedy method, for both forms of the flows."""
        fits = mcmc.best_chain(mcmc.anneal(self.network.flows, self.network.units, self.network.adjacency, variants, reps, chains, seed))
        rows = mcmc.score_rows(fits)
        n = self.network.units.groupBy("network_id").agg(F.count("*").alias("n"))
        for rep in reps:
            best = greedy.best_step(greedy.run(self.network.flows, self.network.units, self.network.adjacency, rep))
            rows = rows.unionByName(best.join(n, "network_id").select("network_id", F.lit("ga").alias("model"), F.lit(rep).alias("rep"), "n", "b", "dl"))
        return rows
