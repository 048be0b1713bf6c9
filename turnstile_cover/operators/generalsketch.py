"""The general fingerprint sketch: a linear state of every column from which pairs of users that a set separates are estimated.

A state holds, for each column, two L0 states and two samples of its coordinates, all of the same seeds, built from
signed updates (i, j, c). The columns of a set are combined into one vector by random integers (equal rows stay
equal, different ones differ), and half the moment complement of that vector at p = 2 is the number of pairs that
differ. Samples come from l0 samplers, or are the users of the smallest hashes with all their entries.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, functions as F

from ..functions.hashing import PRIME, Seed, poly4
from . import l0, l0sampler, submodular
from .cells import merge
from .checkpoints import cut
from .combine import columns
from .moments import HALVES, complement_by, from_draws, half_seeds

ROW_ROLE = 64


@dataclass(frozen=True)
class GeneralSizes:
    """n users; sampler: 'l0' tables of size slots, or 'rowhash' with about rows users; gamma: of the moment complement."""

    n: int
    sampler: str = "l0"
    size: int = 1024
    rows: int = 1250
    slots: int = 1024
    reps: int = 3
    levels: int = 20
    gamma: float = 0.01
    seed: int = 1

    def __post_init__(self):
        if self.sampler not in ("l0", "rowhash"):
            raise ValueError(f"unknown sampler {self.sampler}")


@dataclass
class GeneralState:
    """Of each half: L0 cells and sample cells of every column, and those of the vector of ones."""

    counts: list[DataFrame]
    draws: list[DataFrame]
    unit_counts: list[DataFrame]
    unit_draws: list[DataFrame]

    def tables(self) -> list[DataFrame]:
        return [*self.counts, *self.draws, *self.unit_counts, *self.unit_draws]


def sampled_users(df: DataFrame, sizes: GeneralSizes, half: int) -> DataFrame:
    """Rows of the users whose hash is small: a linear map that selects rows, so deletions cancel."""
    rate = min(1.0, sizes.rows / max(1, sizes.n))
    return df.where(poly4(F.pmod("i", F.lit(PRIME)), Seed.of(half_seeds(sizes.seed, half)[1], ROW_ROLE)) < int(rate * PRIME) + 1)


def build(u: DataFrame, universe: DataFrame, sizes: GeneralSizes, copy: int = 1) -> GeneralState:
    """The state of updates (i, j, c) over the users (i) of the universe; copies of other numbers are independent."""
    s = GeneralSizes(**{**sizes.__dict__, "seed": sizes.seed + 1000 * (copy - 1)})
    ones = universe.select("i", F.lit(1).cast("long").alias("c"))
    none = ones.withColumn("g", F.lit(0))
    state = GeneralState([], [], [], [])
    for half in HALVES:
        a, b = half_seeds(s.seed, half)
        state.counts.append(l0.build(u, ["j"], slots=s.slots, reps=s.reps, levels=s.levels, seed=a))
        state.unit_counts.append(l0.build(none, ["g"], slots=s.slots, reps=s.reps, levels=s.levels, seed=a).drop("g"))
        if s.sampler == "l0":
            state.draws.append(l0sampler.build(u, ["j"], size=s.size, levels=s.levels, seed=b))
            state.unit_draws.append(l0sampler.build(none, ["g"], size=s.size, levels=s.levels, seed=b).drop("g"))
        else:
            rows = sampled_users(u, s, half).groupBy("j", "i").agg(F.sum("c").alias("s0"))
            state.draws.append(rows.where("s0 <> 0"))
            state.unit_draws.append(sampled_users(ones, s, half).select("i", F.col("c").alias("s0")))
    return state


def merged(*states: GeneralState) -> GeneralState:
    """The state of all updates together; the users are those of the first, which all must share."""
    parts = {x: [merge(*(getattr(s, x)[h] for s in states)) for h in HALVES] for x in ("counts", "draws")}
    return GeneralState(parts["counts"], parts["draws"], states[0].unit_counts, states[0].unit_draws)


def separated_pairs(state: GeneralState, sets: DataFrame, sizes: GeneralSizes, copy: int = 1) -> DataFrame:
    """cand, value (estimated pairs that the set's columns separate) and branch, for every set of sets (cand, j)."""
    s = GeneralSizes(**{**sizes.__dict__, "seed": sizes.seed + 1000 * (copy - 1)})
    v = s.seed + 7
    counts = [columns(c, sets, v) for c in state.counts]
    groups = sets.select("cand").distinct()
    if s.sampler == "l0":
        draws = from_draws([columns(d, sets, v) for d in state.draws], state.unit_draws[1], ["cand"], s.size, s.seed)
    else:
        draws = _from_rows([columns(d, sets, v) for d in state.draws], state.unit_draws[1], groups)
    got = complement_by(counts, state.unit_counts[1], draws, groups, ["cand"], s.n, 2, s.gamma, s.slots)
    return got.select("cand", (F.col("complement") / 2).alias("value"), "branch")


def _from_rows(rows: list[DataFrame], users: DataFrame, groups: DataFrame):
    """Samples of whole users: those with a nonzero value, and after the shift those of another value than b."""
    first = rows[0].select("cand", F.col("s0").cast("long").alias("x")).where("x <> 0")

    def second(tops: DataFrame) -> DataFrame:
        here = rows[1].select("cand", F.col("s0").cast("long").alias("x")).where("x <> 0")
        total = users.agg(F.count("*").alias("t"))  # one row
        zeros = groups.join(here.groupBy("cand").agg(F.count("*").alias("m")), "cand", "left").crossJoin(F.broadcast(total))
        zeros = zeros.select("cand", F.lit(0).cast("long").alias("x"), (F.col("t") - F.coalesce("m", F.lit(0))).alias("f"))
        counted = here.groupBy("cand", "x").agg(F.count("*").alias("f")).unionByName(zeros.where("f > 0"))
        return counted.join(tops.select("cand", "b"), "cand").where("x <> b").drop("b")

    return first.groupBy("cand", "x").agg(F.count("*").alias("f")), second


@dataclass
class GeneralSketchFn:
    """Pairs separated, for the noisy greedy: one state for each copy, written once."""

    updates: DataFrame
    universe: DataFrame
    sizes: GeneralSizes
    built: dict[int, GeneralState] = field(default_factory=dict)
    numbers: dict[int, int] = field(default_factory=dict)

    def state(self, copy: int) -> GeneralState:
        if copy not in self.built:
            raw = build(self.updates, self.universe, self.sizes, copy)
            self.built[copy] = GeneralState(*([cut(x) for x in group] for group in (raw.counts, raw.draws, raw.unit_counts, raw.unit_draws)))
            self.numbers[id(self.built[copy])] = copy
        return self.built[copy]

    def query(self, state: GeneralState, sets: DataFrame) -> DataFrame:
        return separated_pairs(state, sets, self.sizes, self.numbers[id(state)]).select("cand", "value")


def select(u: DataFrame, universe: DataFrame, k: int, sizes: GeneralSizes, copies: int = 1) -> DataFrame:
    """round, col, gain, total: k columns by the noisy greedy. copies = k takes a fresh state each round, as the analysis asks;
    copies = 1 serves all rounds from one, as the experiments do."""
    if copies not in (1, k):
        raise ValueError("copies is 1, or one a round")
    return submodular.greedy(GeneralSketchFn(u, universe, sizes), u.select("j").distinct(), k, fresh=copies > 1)


def combined_sql(cells: str, chosen: list[int], seed: int) -> str:
    """L0 cells of the combination of some columns; cells: a query of (j, rep, lvl, slot, s0)."""
    w = f"({Seed.of(seed + 7, 9).sql('j')} % {1 << 20} + 1)"
    return f"SELECT 0 AS g, rep, lvl, slot, sum(s0::HUGEINT * {w}) AS s0 FROM ({cells}) WHERE j IN ({', '.join(map(str, chosen))}) GROUP BY ALL HAVING sum(s0::HUGEINT * {w}) <> 0"

