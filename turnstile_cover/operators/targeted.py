"""Targeted fingerprinting: features that tell one user from the most others."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.hashing import PRIME, Seed, poly4
from ..plans.params import Params
from ..sources.features import Codes, Wide
from . import coverage
from .cells import merge
from .greedy import trajectory
from .l0 import build as build_l0


def exact(w: Wide, user: int, k: int, df: DataFrame | None = None, codes: Codes | None = None) -> DataFrame:
    """Greedy over one-hot features against the target's row: a feature separates the users in whose column they differ.

    Each round is one aggregate over the coded table: the open users' counts by attribute value score every candidate, and the
    number of open users is known from the gain before. df: coded users to count instead of all.
    """
    c = codes or w.codes()
    row = c.df.where(F.col("uid") == user).first()
    spark = w.df.sparkSession
    if row is None:
        return trajectory(spark, [], "string")
    own = [(n, row[a]) for n, a in enumerate(w.attributes)]
    mine = F.lit(False)
    for n, v in own:
        mine = mine | ((F.col("a") == n) & (F.col("v") == v))
    # a value of the target that no open user has still separates them all
    fixed = spark.createDataFrame([(n, v, 0) for n, v in own], "a int, v long, m long")
    open_, picked, rows, total = (c.df if df is None else df).where(F.col("uid") != user), [], [], 0
    left = open_.count()
    for r in range(1, k + 1):
        counts = open_.select(F.explode(c.pairs()).alias("x")).groupBy("x.a", "x.v").agg(F.count("*").alias("m"))
        m = counts.unionByName(fixed).groupBy("a", "v").agg(F.sum("m").alias("m"))
        gains = m.select("a", "v", F.when(mine, F.lit(left) - F.col("m")).otherwise(F.col("m")).alias("g"))
        for n, v in picked:
            gains = gains.where((F.col("a") != n) | (F.col("v") != v))
        best = gains.orderBy(F.desc("g"), "a", "v").first()
        if best is None or best["g"] == 0:  # nothing is won any more: the first feature left of all
            rest = c.df.select(F.explode(c.pairs()).alias("x")).where(~F.struct("x.a", "x.v").isin([F.struct(F.lit(n), F.lit(v).cast("long")) for n, v in picked]) if picked else F.lit(True))
            least = rest.agg(F.min(F.struct("x.a", "x.v")).alias("least")).first()["least"]
            if least is None:
                break
            best = {"a": least["a"], "v": least["v"], "g": 0}
        a = w.attributes[best["a"]]
        picked.append((best["a"], best["v"]))
        total += int(best["g"])
        left -= int(best["g"])
        rows.append((r, c.name(a, best["v"]), int(best["g"]), total))
        same = F.col(a) == best["v"]
        open_ = open_.where(same if picked[-1] in own else ~same)
    return trajectory(spark, rows, "string")


def exact_sql(w: Wide, user: int, k: int) -> str:
    parts = [f"w AS MATERIALIZED ({w.sql})", f"l AS MATERIALIZED ({w.long_sql()})", "fs AS MATERIALIZED (SELECT DISTINCT f FROM l)", f"t AS MATERIALIZED (SELECT f FROM l WHERE uid = {user})", f"o0 AS (SELECT uid FROM w WHERE uid <> {user})"]
    for r in range(1, k + 1):
        taken = " UNION ALL ".join(f"SELECT f FROM r{x}" for x in range(1, r)) or "SELECT ''"
        parts.append(f"r{r} AS MATERIALIZED (SELECT fs.f, CASE WHEN fs.f IN (SELECT f FROM t) THEN (SELECT count(*) FROM o{r - 1}) - coalesce(m, 0) ELSE coalesce(m, 0) END::BIGINT AS g FROM fs LEFT JOIN (SELECT f, count(*) AS m FROM l JOIN o{r - 1} USING (uid) GROUP BY f) c ON c.f = fs.f WHERE fs.f NOT IN ({taken}) ORDER BY g DESC, fs.f LIMIT 1)")
        parts.append(f"o{r} AS MATERIALIZED (SELECT uid FROM o{r - 1} WHERE (uid IN (SELECT uid FROM l WHERE f = (SELECT f FROM r{r}))) = ((SELECT f FROM r{r}) IN (SELECT f FROM t)))")
    rows = " UNION ALL ".join(f"SELECT {r}::INT AS round, f AS col, g AS gain FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} SELECT round, col, gain, sum(gain) OVER (ORDER BY round)::BIGINT AS total FROM ({rows})"


def sampled_rows(df: DataFrame, rate: float, seed: int = 1) -> DataFrame:
    """Users whose hash is under the rate: the same ones in every column and every engine."""
    return df.where(poly4(F.pmod("uid", F.lit(PRIME)), Seed.of(seed, 62)) < int(rate * PRIME))


def exact_raw(w: Wide, user: int, k: int, df: DataFrame | None = None, entry_rate: float = 1.0, seed: int = 1) -> DataFrame:
    """The same over whole attributes; with entry_rate, only hashed entries of the difference count."""
    df = w.df if df is None else df
    row = w.df.where(F.col("uid") == user).first()
    if row is None:
        return trajectory(w.df.sparkSession, [], "string")
    differs = {}
    for n, a in enumerate(w.attributes):
        kept = F.lit(True) if entry_rate >= 1 else poly4((F.pmod("uid", F.lit(PRIME)) + n * 7919) % PRIME, Seed.of(seed, 63)) < int(entry_rate * PRIME)
        differs[a] = ~F.col(a).eqNullSafe(F.lit(row[a])) & kept
    open_, rows, total = df.where(F.col("uid") != user), [], 0
    for r in range(1, min(k, len(w.attributes)) + 1):
        left = [a for a in w.attributes if a not in {x[1] for x in rows}]
        got = open_.agg(*(F.count_if(differs[a]).alias(a) for a in left)).first()
        a = max(left, key=lambda x: (got[x], -w.attributes.index(x)))
        total += got[a]
        rows.append((r, a, int(got[a]), int(total)))
        open_ = open_.where(~differs[a])
    return trajectory(w.df.sparkSession, rows, "string")


def exact_raw_sql(w: Wide, user: int, k: int, where: str = "true", kept: str = "true") -> str:
    """kept: which entries of attribute {n} count."""
    parts = [f"w AS MATERIALIZED ({w.sql})", "l AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT uid, {n} AS a, {a} IS DISTINCT FROM (SELECT {a} FROM w WHERE uid = {user}) AND {kept.format(n=n)} AS x FROM w" for n, a in enumerate(w.attributes)) + ")", f"o0 AS (SELECT uid FROM w WHERE uid <> {user} AND {where})"]
    for r in range(1, k + 1):
        taken = " UNION ALL ".join(f"SELECT a FROM r{x}" for x in range(1, r)) or "SELECT 99"
        parts.append(f"r{r} AS MATERIALIZED (SELECT a, count(*) FILTER (x)::BIGINT AS g FROM l JOIN o{r - 1} USING (uid) WHERE a NOT IN ({taken}) GROUP BY a ORDER BY g DESC, a LIMIT 1)")
        parts.append(f"o{r} AS MATERIALIZED (SELECT uid FROM o{r - 1} WHERE uid NOT IN (SELECT uid FROM l WHERE x AND a = (SELECT a FROM r{r})))")
    names = "[" + ", ".join(f"'{a}'" for a in w.attributes) + "]"
    rows = " UNION ALL ".join(f"SELECT {r}::INT AS round, {names}[a + 1] AS col, g AS gain FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} SELECT round, col, gain, sum(gain) OVER (ORDER BY round)::BIGINT AS total FROM ({rows})"


def rate_sql(rate: float, seed: int = 1) -> str:
    return f"{Seed.of(seed, 62).sql('uid')} < {int(rate * PRIME)}"


def fingerprint_sampled(w: Wide, user: int, k: int, row_rate: float, entry_rate: float = 1.0, seed: int = 1, onehot: bool = True) -> DataFrame:
    """Fixed rates instead of the sketch's levels: greedy on the sampled users and the sampled nonzeros of their difference."""
    if not onehot:
        return exact_raw(w, user, k, sampled_rows(w.df, row_rate, seed), entry_rate, seed)
    c = w.codes()
    if entry_rate >= 1:
        return exact(w, user, k, sampled_rows(c.df, row_rate, seed), c)
    target = c.df.where(F.col("uid") == user).select("uid")
    got = fingerprint_all(w, target, k, row_rate, seed, entry_rate=entry_rate, codes=c).select("uid", F.posexplode(F.arrays_zip("cols", "gains")).alias("pos", "x"))
    total = F.sum("x.gains").over(Window.partitionBy("uid").orderBy("pos"))
    return got.select((F.col("pos") + 1).alias("round"), F.col("x.cols").alias("col"), F.col("x.gains").alias("gain"), total.alias("total"))


def entry_kept(uids: np.ndarray, feature: int, rate: float, seed: int) -> np.ndarray:
    """Is the entry of each user and the feature of this place sampled?"""
    x = (uids % PRIME + feature * 7919) % PRIME
    a, b, c, d = (np.int64(k) for k in Seed.of(seed, 63).coefficients)
    return (((((a * x + b) % PRIME) * x + c) % PRIME) * x + d) % PRIME < int(rate * PRIME)


def entry_kept_sql(feature: str, rate: float, seed: int = 1) -> str:
    return f"{Seed.of(seed, 63).sql(f'((uid + {feature} * 7919) % {PRIME})')} < {int(rate * PRIME)}"


def bitmaps(flags: np.ndarray) -> np.ndarray:
    """Rows of flags as rows of 64-bit words."""
    packed = np.packbits(flags, axis=-1)
    return np.ascontiguousarray(np.pad(packed, [(0, 0), (0, -packed.shape[-1] % 8)])).view(np.uint64)


def difference(has: np.ndarray, own: list[int], everyone: np.ndarray, kept: np.ndarray | None = None) -> np.ndarray:
    """Bitmaps of the users that differ from the target on each feature; own: the target's features."""
    out = has.copy()
    out[own] = ~has[own] & everyone
    return out if kept is None else out & kept


def greedy_bits(differs: np.ndarray, everyone: np.ndarray, k: int) -> tuple[list[int], list[int]]:
    """Features picked and users won by each: k rounds over bitmaps, only words with open users are read again."""
    gains, picks, won, open_ = np.bitwise_count(differs).sum(1, dtype=np.int64), [], [], everyone
    for _ in range(min(k, len(differs))):
        best = int(gains.argmax())
        picks.append(best)
        won.append(int(gains[best]))
        open_ = open_ & ~differs[best]
        some = np.flatnonzero(open_)
        differs, open_ = differs[:, some], open_[some]
        gains = np.bitwise_count(differs & open_).sum(1, dtype=np.int64)
        gains[picks] = -1
    return picks, won


FEW = 1 << 14  # targets by rows that are worked off at once


def shared_greedy(codes: np.ndarray, weights: np.ndarray, everyone: np.ndarray, targets: np.ndarray, k: int, features: np.ndarray, fill: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Greedy for many targets at once: features picked, users of the sample won by each, and users of all left after each.

    codes: different rows, a feature's place for each attribute; weights and everyone: users of the sample and of all with each row;
    features: the attribute of each feature. Users that agree with a target on its picks depend on those alone, so targets with the same
    picks and the same answers share one set of rows, and its counts score every feature for all of them. Without fill, picks after
    the last that can tell anyone apart are left out.
    """
    d, t = len(features), len(targets)
    k = min(k, d)
    picks, won, left = np.zeros((t, k), np.int32), np.zeros((t, k), np.int64), np.zeros((t, k), np.int64)
    todo = [(np.arange(len(codes)), np.arange(t), ())] if t and k else []
    while todo:
        rows, group, taken = todo.pop()
        r, w = len(taken), weights[rows]
        size = int(w.sum())
        if len(rows) <= 1 and not fill:
            left[group, r:] = int(everyone[rows].sum())
            continue
        if len(group) * len(rows) <= FEW:
            picks[group, r:], won[group, r:], left[group, r:] = _few_left(codes[rows], w, everyone[rows], targets[group], taken, k - r, features)
            continue
        m = np.zeros(d, np.int64)
        if size:
            part = codes[rows]
            for a in range(codes.shape[1]):
                m += np.bincount(part[:, a], w, d).astype(np.int64)
        own = targets[group]
        # the best of the target's own features, which separate those without them; ties go to the first feature
        gains = size - m[own]
        gains[np.isin(own, taken)] = -1
        at = gains.argmax(1)
        best, gain = own[np.arange(len(group)), at].astype(np.int64), gains[np.arange(len(group)), at]
        open_, score = np.arange(len(group)), m.copy()
        score[list(taken)] = -1
        for f in np.argsort(-score, kind="stable"):  # the best of the others, for targets that have it the next one
            if score[f] < 0 or not len(open_):
                break
            free = own[open_, features[f]] != f
            x = open_[free]
            better = (score[f] > gain[x]) | ((score[f] == gain[x]) & (f < best[x]))
            best[x[better]], gain[x[better]] = f, score[f]
            open_ = open_[~free]
        picks[group, r], won[group, r] = best, gain
        mine = own[np.arange(len(group)), features[best]] == best
        order = np.lexsort((mine, best))
        key = best[order] * 2 + mine[order]
        edge = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1], [True])))
        for lo, hi in zip(edge[:-1], edge[1:], strict=True):
            f, has = int(key[lo]) >> 1, bool(key[lo] & 1)
            kept, some = rows[(codes[rows, features[f]] == f) == has], group[order[lo:hi]]
            left[some, r] = int(everyone[kept].sum())
            if r + 1 < k:
                todo.append((kept, some, (*taken, f)))
    return picks, won, left


def _few_left(codes: np.ndarray, weights: np.ndarray, everyone: np.ndarray, own: np.ndarray, taken: tuple[int, ...], k: int, features: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The last k rounds of shared_greedy for targets by rows at once. The users that differ from a target on an attribute are all
    won by its own feature, so another feature can only be its equal: where all of them have one value that comes first."""
    t, n = len(own), len(codes)
    every, high = np.arange(t), 1 << 30
    same = codes[None] == own[:, None]
    open_, stay = np.repeat(weights[None] > 0, t, 0), np.ones((t, n), bool)
    picks = np.full((t, len(taken) + k), -1, np.int64)
    picks[:, : len(taken)] = taken
    won, left = np.zeros((t, k), np.int64), np.zeros((t, k), np.int64)
    for r in range(k):
        w = np.where(open_, weights[None], 0).astype(np.float64)
        gains = np.rint(w.sum(1)[:, None] - (w[:, None] @ same)[:, 0]).astype(np.int64) if n else np.zeros(own.shape, np.int64)
        a = gains.argmax(1)
        gain, mine = gains[every, a], own[every, a].astype(np.int64)
        first = np.zeros(t, np.int64)
        for _ in range(len(taken) + r + 1):
            first += (picks == first[:, None]).any(1)
        if n:
            value = codes[:, a].T.astype(np.int64)
            other = open_ & (value != mine[:, None])
            low, top = np.where(other, value, high).min(1), np.where(other, value, -1).max(1)
            mine = np.where((low == top) & (low < mine), low, mine)
        best = np.where(gain > 0, mine, first)
        picks[:, len(taken) + r], won[:, r] = best, gain
        agree = (codes[:, features[best]].T == best[:, None]) == (own[every, features[best]] == best)[:, None]
        open_ &= agree
        stay &= agree
        left[:, r] = stay @ everyone.astype(np.int64)
    return picks[:, len(taken) :], won, left


@dataclass(frozen=True)
class Rows:
    """The different rows of a coded table on the driver: features (attribute, code), each row's features, and counts of users."""

    features: list[tuple[int, int]]
    codes: np.ndarray
    counts: dict[str, np.ndarray]

    @property
    def attribute(self) -> np.ndarray:
        return np.array([a for a, _ in self.features], np.int64)

    def places(self, columns: list[np.ndarray]) -> np.ndarray:
        """Places of the features of rows given by columns of codes."""
        out, first = [], 0
        for a, x in enumerate(columns):
            values = np.array([v for n, v in self.features if n == a], np.int64)
            out.append(first + np.searchsorted(values, x))
            first += len(values)
        return np.stack(out, 1).astype(np.int32) if out else np.zeros((0, 0), np.int32)


def different_rows(df: DataFrame, attributes: tuple[str, ...], features: list[tuple[int, int]], counts: dict[str, Column], max_bytes: int) -> Rows:
    """Users with equal rows collapse to one with counts; the rows must fit max_bytes, since they go to every executor."""
    from .checkpoints import cut

    rows = cut(df.groupBy(*attributes).agg(*(x.alias(n) for n, x in counts.items())))
    n, each = rows.count(), (2 if len(features) < 1 << 15 else 4) * len(attributes) + 4 * len(counts)
    if n * each > max_bytes:
        raise ValueError(f"{n} different rows of {each} bytes do not fit {max_bytes} bytes: take fewer rates and seeds at a time, or a lower row rate")
    table = rows.toArrow()
    out = Rows(features, np.zeros((0, 0)), {x: table.column(x).to_numpy().astype(np.int32) for x in counts})
    codes = out.places([table.column(a).to_numpy() for a in attributes])
    return Rows(features, codes.astype(np.int16) if len(features) < 1 << 15 else codes, out.counts)


def dictionary(c: Codes) -> list[tuple[int, int]]:
    """The features (attribute, code) in order."""
    return sorted((r["a"], r["v"]) for r in c.df.select(F.explode(c.pairs()).alias("x")).select("x.*").distinct().collect())


def sweep_rows(c: Codes, k: int, rates: list[float], seeds: int, users: DataFrame, max_bytes: int) -> DataFrame:
    """For every different row of the users as target, rate and seed: its attributes, rate, seed, k and separated (of all users)."""
    spark, df, attributes = c.df.sparkSession, c.df, c.attributes
    df = df.join(users.select("uid").distinct().withColumn("t_", F.lit(1)), "uid", "left")
    counts = {"n": F.count("*"), "t": F.count("t_")}
    samples = [(rate, seed) for rate in rates for seed in range(1, seeds + 1)]
    for i, (rate, seed) in enumerate(samples):
        counts[f"s{i}"] = F.count_if(poly4(F.pmod("uid", F.lit(PRIME)), Seed.of(seed, 62)) < int(rate * PRIME))
    rows = different_rows(df, attributes, dictionary(c), counts, max_bytes)
    n = int(rows.counts["n"].sum())
    parts = max(1, min(-(-len(rows.codes) // 2000), 4 * spark.sparkContext.defaultParallelism * 2 // max(1, len(samples)) + 1))
    shared = spark.sparkContext.broadcast(rows)
    schema = ", ".join(f"{a} long" for a in attributes) + ", rate double, seed int, k int, separated long"

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows = shared.value
        for pdf in batches:
            for task in pdf["id"]:
                i, part = divmod(int(task), parts)
                mine = np.flatnonzero(rows.counts["t"] > 0)
                # neighbours in the order of rows share picks
                mine = mine[np.lexsort(rows.codes[mine].T)] if len(mine) else mine
                mine = np.array_split(mine, parts)[part]
                left = shared_greedy(rows.codes, rows.counts[f"s{i}"], rows.counts["n"], rows.codes[mine], k, rows.attribute, False)[2]
                for r in range(left.shape[1] if len(mine) else 0):
                    out = {a: np.array([v for _, v in rows.features])[rows.codes[mine, x]] for x, a in enumerate(attributes)} | {"separated": n - left[:, r]}
                    yield pd.DataFrame(out).assign(rate=samples[i][0], seed=samples[i][1], k=r + 1)[[x.split()[0] for x in schema.split(", ")]]

    tasks = len(samples) * parts
    return spark.range(0, tasks, 1, tasks).mapInPandas(run, schema)


def sweep(w: Wide, users: DataFrame, k: int, rates: list[float], seeds: int, max_bytes: int = 400_000_000, codes: Codes | None = None) -> DataFrame:
    """uid, rate, seed, k and separated (of all users, by the first k features picked on the sample), for every target, rate and
    seed in one pass: the different rows with their counts in every sample go to the executors if they fit max_bytes."""
    c = codes or w.codes()
    found = sweep_rows(c, k, rates, seeds, users, max_bytes)
    targets = c.df.join(users.select("uid"), "uid", "left_semi").select("uid", *w.attributes)
    return targets.join(found, list(w.attributes)).select("uid", "rate", "seed", "k", "separated")


CELLS = 1 << 17  # pairs of a group and a row, or counts of groups, that are worked off at once


def sampled_by(uids: np.ndarray, seed: int) -> np.ndarray:
    """The hash of sampled_rows."""
    x = uids % PRIME
    a, b, c, d = (np.int64(k) for k in Seed.of(seed, 62).coefficients)
    return ((((a * x + b) % PRIME * x + c) % PRIME) * x + d) % PRIME


def same_rows(codes: np.ndarray, spans: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Places of the first of each of the different rows, and each row's number among them; spans: values of each attribute."""
    key, span = np.zeros(len(codes), np.int64), 1
    for a, many in enumerate(spans):
        if span * many >= 1 << 62:
            _, key = np.unique(key, return_inverse=True)
            span = len(codes) + 1
        key, span = key * many + codes[:, a], span * many
    _, first, number = np.unique(key, return_index=True, return_inverse=True)
    return first, number


@dataclass(frozen=True)
class Best:
    """What greedy picks for targets in groups of rows, from the counts (groups by values) of each attribute."""

    counts: list[np.ndarray]
    size: np.ndarray

    @classmethod
    def of(cls, group: np.ndarray, codes: np.ndarray, weights: np.ndarray, groups: int, spans: list[int]) -> Best:
        counts = [np.bincount(group * many + codes[:, a], weights, groups * many).reshape(groups, many) for a, many in enumerate(spans)]
        return cls(counts, np.bincount(group, weights, groups))

    def pick(self, group: np.ndarray, own: np.ndarray, taken: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Attribute and value picked by each target (group, values); taken: attributes and values picked before, by group. The target's own
        value wins all users that differ on its attribute, so another value only ties where all of them have it, and goes first if lower."""
        gain, a = np.zeros(len(group)), np.zeros(len(group), np.int64)
        for n, m in enumerate(self.counts):
            won = self.size[group] - m[group, own[:, n]]
            better = won > gain
            gain[better], a[better] = won[better], n
        v = own[np.arange(len(group)), a].astype(np.int64)
        for n, m in enumerate(self.counts):
            some = np.flatnonzero((a == n) & (gain > 0))
            if len(some):
                at, mine = group[some], own[some, n].astype(np.int64)
                has = m > 0
                there = m[at, mine] > 0
                one = has.sum(1)[at] - there == 1
                other = (has @ np.arange(m.shape[1]))[at] - np.where(there, mine, 0)
                v[some] = np.where(one & (other < mine), other, mine)
        none = np.flatnonzero(gain <= 0)
        if len(none):  # nothing is won any more: the first feature left
            base = np.cumsum([0] + [m.shape[1] for m in self.counts])
            places, first = base[taken[:, :, 0]] + taken[:, :, 1], np.zeros(len(taken), np.int64)
            for _ in range(taken.shape[1]):
                first += (places == first[:, None]).any(1)
            first = first[group[none]]
            a[none] = np.searchsorted(base, first, "right") - 1
            v[none] = first - base[a[none]]
        return a, v


def left_by_round(codes: np.ndarray, weights: np.ndarray, everyone: np.ndarray, targets: np.ndarray, taken: list[tuple[int, int]], k: int, spans: list[int]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Rounds of shared_greedy for targets that are among the rows (places), all groups of equal picks at a time: rounds, targets and the
    users left to each after that round; a round of -r stands for all from r to k. taken: the picks before, the same for all."""
    rows = np.arange(len(codes))
    todo = [(np.zeros(len(rows), np.int64), rows, np.zeros(len(targets), np.int64), targets, np.array([taken], np.int64).reshape(1, len(taken), 2))]
    while todo:
        pg, pr, tg, tr, taken_ = todo.pop()
        groups, r, own = len(taken_), taken_.shape[1] + 1, codes[tr]
        part = codes[pr]
        a, v = Best.of(pg, part, weights[pr], groups, spans).pick(tg, own, taken_)
        has = own[np.arange(len(tr)), a] == v
        widest = max(spans)
        keys, ng = np.unique(((tg * len(spans) + a) * widest + v) * 2 + has, return_inverse=True)
        kh, kv, rest = keys % 2 == 1, keys // 2 % widest, keys // 2 // widest
        ka, kg = rest % len(spans), rest // len(spans)
        gs, rs = [], []
        for n, many in enumerate(spans):  # rows that have the picked value
            mine = np.flatnonzero((ka == n) & kh)
            if len(mine):
                to = np.full(groups * many, -1, np.int64)
                to[kg[mine] * many + kv[mine]] = mine
                at = to[pg * many + part[:, n]]
                some = np.flatnonzero(at >= 0)
                gs.append(at[some])
                rs.append(pr[some])
        without = np.flatnonzero(~kh)
        if len(without):  # rows that lack it
            order = np.argsort(pg, kind="stable")
            start = np.searchsorted(pg[order], np.arange(groups + 1))
            for lo in range(0, len(without), 4096):
                some = without[lo : lo + 4096]
                many = (start[1:] - start[:-1])[kg[some]]
                g = np.repeat(some, many)
                at = order[np.arange(len(g)) - np.repeat(np.cumsum(many) - many, many) + np.repeat(start[kg[some]], many)]
                stay = part[at, ka[g]] != kv[g]
                gs.append(g[stay])
                rs.append(pr[at[stay]])
        gs, rs = np.concatenate(gs), np.concatenate(rs)
        left, size = np.bincount(gs, everyone[rs], len(keys)).astype(np.int64), np.bincount(gs, minlength=len(keys))
        done = (size <= 1) | (r == k)
        over = done[ng]
        yield -r, tr[over], left[ng[over]]
        if done.all():
            continue
        yield r, tr[~over], left[ng[~over]]
        place = np.cumsum(~done) - 1
        stay = ~done[gs]
        gs, rs, tg, tr = place[gs[stay]], rs[stay], place[ng[~over]], tr[~over]
        going = ~done
        picked = np.concatenate((taken_[kg[going]], np.stack((ka[going], kv[going]), 1)[:, None]), 1)
        size = size[going]
        work = np.cumsum(np.maximum(size, sum(spans) // 4))
        cuts = np.searchsorted(work, np.arange(CELLS, work[-1], CELLS), "right")
        cuts = np.unique(np.concatenate(([0], cuts, [len(size)])))
        if len(cuts) > 2:
            o, p = np.argsort(gs, kind="stable"), np.argsort(tg, kind="stable")
            gs, rs, tg, tr = gs[o], rs[o], tg[p], tr[p]
        for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
            x, y = (slice(*np.searchsorted(z, (lo, hi))) for z in (gs, tg)) if len(cuts) > 2 else (slice(None), slice(None))
            todo.append((gs[x] - lo, rs[x], tg[y] - lo, tr[y], picked[lo:hi]))


def sweep_totals(c: Codes, k: int, rates: list[float], seeds: int) -> DataFrame:
    """rate, seed, k, separated (mean over all users as targets), least and users.

    The counts of the whole table give every target's first pick. Users that agree with it on that pick then go to one task, so no
    table of rows is sent whole to the driver or to an executor; there equal rows become one, and each sample's rounds run on them.
    """
    spark, attributes = c.df.sparkSession, list(c.attributes)
    features, samples = dictionary(c), [(rate, seed) for rate in rates for seed in range(1, seeds + 1)]
    schema = "rate double, seed int, k int, separated double, least long, users long"
    values = [np.array([v for n, v in features if n == a], np.int64) for a in range(len(attributes))]
    spans, k = [len(x) for x in values], min(k, len(features))
    if not features or k < 1 or not samples:
        return spark.createDataFrame([], schema)
    kind = np.int16 if max(spans) < 1 << 15 else np.int32

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for b in batches:
            if b.num_rows:
                yield b.column("uid").to_numpy().astype(np.int64), np.stack([np.searchsorted(x, b.column(a).to_numpy()) for a, x in zip(attributes, values, strict=True)], 1).astype(kind)

    def kept(uids: np.ndarray) -> Iterator[np.ndarray]:
        """Is each user in each sample?"""
        hashes = [sampled_by(uids, seed) for seed in range(1, seeds + 1)]
        return (hashes[seed - 1] < int(rate * PRIME) for rate, seed in samples)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = [np.zeros((len(samples), many), np.int64) for many in spans]
        users = 0
        for uids, codes in coded(batches):
            users += len(uids)
            for i, some in enumerate(kept(uids)):
                part = codes[some]
                for a, many in enumerate(spans):
                    total[a][i] += np.bincount(part[:, a], minlength=many)
        rows = [(a, *np.nonzero(t), t[np.nonzero(t)]) for a, t in enumerate(total)]
        out = [np.concatenate([np.full(len(x[1]), x[0]) for x in rows] + [[-1]]), *(np.concatenate([x[n] for x in rows] + [[last]]) for n, last in ((1, 0), (2, 0), (3, users)))]
        yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in out], names=["a", "s", "v", "m"])

    narrow = c.df.select("uid", *attributes)
    counts, n = [np.zeros((len(samples), many)) for many in spans], 0
    for r in narrow.mapInArrow(count, "a long, s long, v long, m long").groupBy("a", "s", "v").agg(F.sum("m").alias("m")).collect():
        if r["a"] < 0:
            n = r["m"]
        else:
            counts[r["a"]][r["s"], r["v"]] = r["m"]
    root, nothing = Best(counts, counts[0].sum(1)), np.zeros((len(samples), 0, 2), np.int64)
    widest = max(spans)

    def first_pick(codes: np.ndarray, i: int) -> np.ndarray:
        """Key of the first pick of each row as a target in sample i."""
        a, v = root.pick(np.full(len(codes), i), codes, nothing)
        return (a * widest + v) * 2 + (codes[np.arange(len(codes)), a] == v)

    def picked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = set()
        for _, codes in coded(batches):
            for i in range(len(samples)):
                found.update((i, int(x)) for x in np.unique(first_pick(codes, i)))
        yield pa.RecordBatch.from_arrays([pa.array([x[p] for x in sorted(found)], pa.int64()) for p in (0, 1)], names=["s", "key"])

    by_key: dict[int, list[int]] = {}
    for r in narrow.mapInArrow(picked, "s long, key long").distinct().collect():
        by_key.setdefault(r["key"], []).append(r["s"])

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Users by the first picks that they agree with, many to a row."""
        for uids, codes in coded(batches):
            out = []
            for key in by_key:
                some = np.flatnonzero((codes[:, key // 2 // widest] == key // 2 % widest) == bool(key % 2))
                if len(some):
                    out.append((key, uids[some].tobytes(), codes[some].tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.binary()), pa.array([x[2] for x in out], pa.binary())], names=["key", "uids", "codes"])

    def rounds(group: pa.Table) -> pa.Table:
        key = group.column("key")[0].as_py()
        uids = np.concatenate([np.frombuffer(x.as_py(), np.int64) for x in group.column("uids")])
        codes = np.concatenate([np.frombuffer(x.as_py(), kind).reshape(-1, len(spans)) for x in group.column("codes")])
        first, number = same_rows(codes, spans)
        codes, everyone = codes[first], np.bincount(number)
        out, mine = [], set(by_key[key])
        for i, some in enumerate(kept(uids)):
            if i not in mine:
                continue
            targets = np.flatnonzero(first_pick(codes, i) == key)
            separated, least, users = np.zeros(k + 1), np.full(k + 1, n), np.zeros(k + 1, np.int64)

            def note(r: int, many: np.ndarray, left: np.ndarray) -> None:
                at = slice(-r, None) if r < 0 else slice(r, r + 1)
                if len(left):
                    separated[at] += float(((n - left) * many).sum())
                    least[at] = np.minimum(least[at], n - left.max())
                    users[at] += many.sum()

            note(-1 if len(codes) <= 1 or k == 1 else 1, everyone[targets], np.full(len(targets), everyone.sum()))
            if len(codes) > 1 and k > 1 and len(targets):
                weights = np.bincount(number[some], minlength=len(codes)).astype(np.float64)
                for r, who, left in left_by_round(codes, weights, everyone, targets, [(key // 2 // widest, key // 2 % widest)], k, spans):
                    note(r, everyone[who], left)
            out += [(*samples[i], r, separated[r], int(least[r]), int(users[r])) for r in range(1, k + 1) if users[r]]
        return pa.Table.from_arrays([pa.array([x[p] for x in out], t) for p, t in enumerate((pa.float64(), pa.int32(), pa.int32(), pa.float64(), pa.int64(), pa.int64()))], names=[x.split()[0] for x in schema.split(", ")])

    tasks = max(1, 2 * len(by_key))
    dealt = narrow.mapInArrow(deal, "key long, uids binary, codes binary").repartition(tasks, "key")
    found = dealt.groupBy("key").applyInArrow(rounds, schema)
    return found.groupBy("rate", "seed", "k").agg((F.sum("separated") / F.sum("users")).alias("separated"), F.min("least").alias("least"), F.sum("users").alias("users"))


def fingerprint_all(w: Wide, users: DataFrame, k: int, row_rate: float, seed: int = 1, max_cells: int = 400_000_000, entry_rate: float = 1.0, codes: Codes | None = None) -> DataFrame:
    """uid, cols, gains and separated_in_sample for every user as target: the sample's different rows go to the executors if they fit
    max_cells bytes (else an error says to lower the row rate), and every different row of the targets is answered once.
    entry_rate keeps each nonzero of the difference by a hash of user and feature. A row rate of 1 is the exact method for many
    targets at once."""
    c = codes or w.codes()
    if entry_rate < 1:
        return _by_entries(w, c, users, k, row_rate, seed, max_cells, entry_rate)
    attributes = w.attributes
    rows = different_rows(sampled_rows(c.df, row_rate, seed), attributes, dictionary(c), {"n": F.count("*")}, max_cells)
    names = [c.name(attributes[a], v) for a, v in rows.features]
    shared = w.df.sparkSession.sparkContext.broadcast((rows, names))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows, names = shared.value
        named = np.array(names, object)
        parts = [pdf for pdf in batches if len(pdf)]
        if parts:
            pdf = pd.concat(parts, ignore_index=True)
            own = rows.places([pdf[a].to_numpy() for a in attributes])
            picks, won, _ = shared_greedy(rows.codes.reshape(-1, len(attributes)), rows.counts["n"], rows.counts["n"], own, k, rows.attribute)
            for lo in range(0, len(pdf), 10_000):
                out = pdf.iloc[lo : lo + 10_000].copy()
                out["cols"], out["gains"] = list(named[picks[lo : lo + 10_000]]), list(won[lo : lo + 10_000])
                out["separated_in_sample"] = won[lo : lo + 10_000].sum(1)
                yield out

    targets = c.df.join(users.select("uid"), "uid", "left_semi").select("uid", *attributes)
    tasks = 2 * w.df.sparkSession.sparkContext.defaultParallelism
    found = targets.select(*attributes).distinct().repartition(tasks).mapInPandas(run, ", ".join(f"{a} long" for a in attributes) + ", cols array<string>, gains array<long>, separated_in_sample long")
    return targets.join(found, list(attributes)).select("uid", "cols", "gains", "separated_in_sample")


def _by_entries(w: Wide, c: Codes, users: DataFrame, k: int, row_rate: float, seed: int, max_cells: int, entry_rate: float) -> DataFrame:
    """The same with sampled entries, which differ between users with equal rows: one bitmap a feature, max_cells cells of one bit."""
    features = dictionary(c)
    names = [c.name(w.attributes[a], v) for a, v in features]
    sample = sampled_rows(c.df, row_rate, seed)
    n = sample.count()
    if n * len(features) > max_cells:
        raise ValueError(f"a sample of {n} users and {len(features)} features does not fit {max_cells} cells: lower the row rate")
    table = sample.select("uid", *w.attributes).toArrow()
    columns = [table.column(a).to_numpy() for a in w.attributes]
    has = bitmaps(np.stack([columns[a] == v for a, v in features])) if features else np.zeros((0, 0), np.uint64)
    uids = table.column("uid").to_numpy()
    kept = bitmaps(np.stack([entry_kept(uids, f, entry_rate, seed) for f in range(len(features))])) 
    attributes = w.attributes
    shared = w.df.sparkSession.sparkContext.broadcast((features, names, has, kept, bitmaps(np.ones((1, n), bool))[0]))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        features, names, has, kept, everyone = shared.value
        place = {f: i for i, f in enumerate(features)}
        for pdf in batches:
            out = []
            for uid, row in zip(pdf["uid"], zip(*(pdf[a] for a in attributes), strict=True), strict=True):
                picks, won = greedy_bits(difference(has, [place[x] for x in enumerate(row)], everyone, kept), everyone, k)
                out.append((uid, [names[x] for x in picks], won, sum(won)))
            yield pd.DataFrame(out, columns=["uid", "cols", "gains", "separated_in_sample"])

    targets = c.df.join(users.select("uid"), "uid", "left_semi").select("uid", *w.attributes)
    return targets.mapInPandas(run, f"uid {c.df.schema['uid'].dataType.simpleString()}, cols array<string>, gains array<long>, separated_in_sample long")


def sampled_onehot_sql(w: Wide, user: int, k: int, row_rate: float, entry_rate: float, seed: int = 1) -> str:
    """One target with sampled rows and entries, by SQL."""
    parts = [f"w AS MATERIALIZED ({w.sql})", f"l AS MATERIALIZED ({w.long_sql()})", "fs AS MATERIALIZED (SELECT f, row_number() OVER (ORDER BY f) - 1 AS n FROM (SELECT DISTINCT f FROM l))", f"t AS MATERIALIZED (SELECT f FROM l WHERE uid = {user})"]
    rows = f"SELECT uid FROM w WHERE {rate_sql(row_rate, seed)}"
    parts.append(f"x AS MATERIALIZED (SELECT s.uid, fs.f FROM ({rows}) s CROSS JOIN fs LEFT JOIN l ON l.uid = s.uid AND l.f = fs.f WHERE (l.f IS NULL) = (fs.f IN (SELECT f FROM t)) AND {entry_kept_sql('n', entry_rate, seed).replace('uid', 's.uid')})")
    parts.append(f"o0 AS ({rows})")
    for r in range(1, k + 1):
        taken = " UNION ALL ".join(f"SELECT f FROM r{y}" for y in range(1, r)) or "SELECT ''"
        parts.append(f"r{r} AS MATERIALIZED (SELECT fs.f, count(o.uid)::BIGINT AS g FROM fs LEFT JOIN (SELECT x.uid, x.f FROM x JOIN o{r - 1} USING (uid)) o ON o.f = fs.f WHERE fs.f NOT IN ({taken}) GROUP BY fs.f ORDER BY g DESC, fs.f LIMIT 1)")
        parts.append(f"o{r} AS MATERIALIZED (SELECT uid FROM o{r - 1} WHERE uid NOT IN (SELECT uid FROM x WHERE f = (SELECT f FROM r{r})))")
    out = " UNION ALL ".join(f"SELECT {r}::INT AS round, f AS col, g AS gain FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} SELECT round, col, gain, sum(gain) OVER (ORDER BY round)::BIGINT AS total FROM ({out})"


def matching_users(w: Wide, user: int, cols: list[str]) -> DataFrame:
    """One row: other users with the target's values on all of cols."""
    row = w.df.where(F.col("uid") == user).select(*(F.col(c).alias(f"t_{c}") for c in cols))  # one row
    same = [F.col(c).eqNullSafe(F.col(f"t_{c}")) for c in cols]
    hit = same[0]
    for s in same[1:]:
        hit = hit & s
    return w.df.where(F.col("uid") != user).crossJoin(F.broadcast(row)).agg(F.count_if(hit).alias("matching"))


def track_row(u: DataFrame, user: int) -> DataFrame:
    """The target's row (j, v), kept beside the sketch."""
    return u.where(F.col("i") == user).groupBy("j").agg(F.sum("c").alias("v"))


def sketch_state(u: DataFrame, params: Params) -> tuple[DataFrame, DataFrame]:
    return coverage.build_sketch(u, params)


def fingerprint(u: DataFrame, universe: DataFrame, row: DataFrame, params: Params) -> DataFrame:
    """Features of a target (its row: j, v; it may be no user's) from linear states: the row is subtracted from every user's
    by adding to the state the state of -v for each user and column, then maximum coverage answers."""
    ones = universe.select("i").crossJoin(F.broadcast(row.where("v <> 0"))).select("i", "j", (-F.col("v")).alias("c"))  # at most d columns
    state, unit = coverage.build_sketch(u, params), coverage.build_sketch(ones, params)
    return coverage.max_coverage((merge(state[0], unit[0]), merge(state[1], unit[1])), params)


def shifted_columns(u: DataFrame, universe: DataFrame, row: DataFrame, params: Params) -> DataFrame:
    """Column L0 cells of the difference: the state of ones is the same for every column, so it is built once and scaled."""
    cells = build_l0(u, ["j"], "i", params.l0_slots, params.l0_reps, params.levels, params.seed)
    ones = build_l0(universe.select("i", F.lit(1).cast("long").alias("c"), F.lit(0).alias("g")), ["g"], "i", params.l0_slots, params.l0_reps, params.levels, params.seed).drop("g")
    spread = ones.crossJoin(F.broadcast(row)).select("j", "rep", "lvl", "slot", (-F.col("v") * F.col("s0")).alias("s0"))
    return merge(cells, spread)

