"""General fingerprinting: features that separate the most pairs of users."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ..functions.hashing import PRIME, Seed, poly4
from ..sources.features import Codes, Wide
from .greedy import trajectory
from .moments import complement_of_sample


def pairs(n: int) -> int:
    return n * (n - 1) // 2


def separated_pairs(wide: DataFrame, cols: list[str]) -> DataFrame:
    """One row: pairs of users that differ on some column: (n^2 - sum f^2) / 2."""
    f = wide.groupBy(*cols).agg(F.count("*").alias("f"))
    n2, squares = F.sum("f").cast("decimal(38,0)"), F.sum(F.col("f").cast("decimal(19,0)") * F.col("f").cast("decimal(19,0)"))
    return f.agg(F.coalesce(((n2 * n2 - squares) / 2).cast("long"), F.lit(0)).alias("separated"))


def _squares(f: str):
    return F.sum(F.col(f).cast("decimal(19,0)") * F.col(f).cast("decimal(19,0)")).cast("decimal(38,0)")


def greedy_raw(w: Wide, k: int, n: int | None = None, codes: Codes | None = None) -> DataFrame:
    """Exact greedy over whole attributes: one aggregate a round scores every candidate; ties go to the first attribute."""
    c = codes or w.codes()
    n = n if n is not None else c.df.count()
    picked, rows, before = [], [], 0
    for r in range(1, min(k, len(w.attributes)) + 1):
        counts = c.df.select(*picked, F.explode(c.pairs(picked)).alias("o")).groupBy(*picked, "o.a", "o.v").agg(F.count("*").alias("f"))
        best = counts.groupBy("a").agg(_squares("f").alias("s")).orderBy("s", "a").first()
        total = (n * n - int(best["s"])) // 2
        picked.append(w.attributes[best["a"]])
        rows.append((r, picked[-1], total - before, total))
        before = total
    return trajectory(w.df.sparkSession, rows, "string")


def onehot_gains(c: Codes, cls: Column, most: int) -> tuple[list[tuple[int, int, int]], int]:
    """The features of the greatest gains as (-gain, place of the attribute, code) in order, and the greatest gain of one left out
    (-1: none is). One aggregate by class and feature; the classes' sizes are the sums over one attribute."""
    by = ["cls", *(["base"] if "base" in c.df.columns else [])]
    m = c.df.select(cls.alias("cls"), *by[1:], F.explode(c.pairs()).alias("x")).groupBy(*by, "x.a", "x.v").agg(F.count("*").alias("m"))
    sized = m.withColumn("n", F.sum(F.when(F.col("a") == 0, F.col("m"))).over(Window.partitionBy(*by))).where(F.col("v").isNotNull())
    cut_ = F.sum(F.col("m").cast("decimal(19,0)") * (F.col("n") - F.col("m")).cast("decimal(19,0)")).cast("decimal(38,0)")
    rows = sized.groupBy("a", "v").agg(cut_.alias("g")).orderBy(F.desc("g"), "a", "v").limit(most + 1).collect()
    return [(-int(r["g"]), r["a"], r["v"]) for r in rows[:most]], int(rows[most]["g"]) if len(rows) > most else -1


def gains_of(c: Codes, cls: Column, features: list[tuple[int, int]]) -> list[int]:
    """Gains of the given features: one count by class for each, and no row for each attribute."""
    hit = [F.count_if(F.col(c.attributes[a]) == v).alias(f"m{i}") for i, (a, v) in enumerate(features)]
    by = c.df.groupBy(cls.alias("cls"), *(["base"] if "base" in c.df.columns else [])).agg(F.count("*").alias("n"), *hit)
    each = by.select("n", F.posexplode(F.array(*(f"m{i}" for i in range(len(features))))).alias("i", "m"))
    cut_ = F.sum(F.col("m").cast("decimal(19,0)") * (F.col("n") - F.col("m")).cast("decimal(19,0)")).cast("decimal(38,0)")
    found = {r["i"]: int(r["g"]) for r in each.groupBy("i").agg(cut_.alias("g")).collect()}
    return [found.get(i, 0) for i in range(len(features))]


def greedy_onehot(w: Wide, k: int, n: int | None = None, codes: Codes | None = None, most: int = 4096, batch: int = 32, lazy_from: int = 2_000_000) -> DataFrame:
    """Exact greedy over one-hot features. A user's class is the bits of the picked features; a feature splits a class of n into m and
    n - m. Gains never rise as classes split, so those of earlier rounds are bounds: the features of the greatest bounds are counted
    anew, a batch in one aggregate, until the best of all is one of this round. Of more than most features the rest keep one bound,
    and all are counted where it is reached. With fewer than lazy_from users all are counted in every round: plans cost more than rows
    there. Ties go to the first feature by attribute, then value."""
    c = codes or w.codes()
    n = n if n is not None else c.df.count()
    cls, picked, rows, before = F.lit(0).cast("long"), set(), [], 0
    bounds, rest = onehot_gains(c, cls, most)
    fresh = {x[1:] for x in bounds}
    for r in range(1, k + 1):
        if picked and len(picked) % 62 == 0 and r > 1:  # bits of a long: classes are named anew
            from .checkpoints import cut

            c, cls = replace(c, df=cut(c.df.withColumn("base", F.xxhash64(cls, *(["base"] if "base" in c.df.columns else []))))), F.lit(0).cast("long")
        if r > 1 and n < lazy_from:
            bounds, rest = onehot_gains(c, cls, most + len(picked))
            bounds = [x for x in bounds if x[1:] not in picked]
            fresh = {x[1:] for x in bounds}
        while bounds and bounds[0][1:] not in fresh:
            stale = [x[1:] for x in bounds if x[1:] not in fresh][:batch]
            gains = dict(zip(stale, gains_of(c, cls, stale), strict=True))
            bounds = sorted((-gains[x[1:]], *x[1:]) if x[1:] in gains else x for x in bounds)
            fresh |= set(stale)
        if rest >= 0 and (not bounds or rest >= -bounds[0][0]):
            bounds, rest = onehot_gains(c, cls, most + len(picked))
            bounds = [x for x in bounds if x[1:] not in picked]
        if not bounds:
            break
        gain, a, v = -bounds[0][0], *bounds[0][1:]
        picked.add((a, v))
        bounds, fresh = bounds[1:], set()
        before += gain
        rows.append((r, c.name(w.attributes[a], v), gain, before))
        cls = cls * 2 + F.coalesce((F.col(w.attributes[a]) == v).cast("long"), F.lit(0))
    return trajectory(w.df.sparkSession, rows, "string")


def greedy_raw_sql(w: Wide, k: int) -> str:
    """Class refinement as one SQL text, over long rows of attribute and value."""
    parts = [f"w AS MATERIALIZED ({w.sql})", "l AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT uid, {n} AS a, CAST({a} AS VARCHAR) AS v FROM w" for n, a in enumerate(w.attributes)) + ")", "k0 AS (SELECT uid, 0::UBIGINT AS c FROM w)", "t0 AS (SELECT (count(*)::HUGEINT) ^ 2 AS s FROM w)"]
    for r in range(1, k + 1):
        taken = " UNION ALL ".join(f"SELECT a FROM r{x}" for x in range(1, r)) or "SELECT 99"
        parts.append(f"r{r} AS MATERIALIZED (SELECT a, sum(f * f)::HUGEINT AS s FROM (SELECT a, c, v, count(*)::HUGEINT AS f FROM l JOIN k{r - 1} USING (uid) WHERE a NOT IN ({taken}) GROUP BY ALL) GROUP BY a ORDER BY s, a LIMIT 1)")
        parts.append(f"k{r} AS MATERIALIZED (SELECT uid, hash(c, v) AS c FROM k{r - 1} JOIN l USING (uid) WHERE a = (SELECT a FROM r{r}))")
    names = "[" + ", ".join(f"'{a}'" for a in w.attributes) + "]"
    rows = " UNION ALL ".join(f"SELECT {r}::INT AS round, {names}[a + 1] AS col, (((SELECT count(*)::HUGEINT FROM w) * (SELECT count(*)::HUGEINT FROM w) - s) // 2)::BIGINT AS total FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} SELECT round, col, (total - coalesce(lag(total) OVER (ORDER BY round), 0))::BIGINT AS gain, total FROM ({rows})"


def greedy_onehot_sql(w: Wide, k: int) -> str:
    parts = [f"w AS MATERIALIZED ({w.sql})", f"l AS MATERIALIZED ({w.long_sql()})", "k0 AS (SELECT uid, 0::BIGINT AS c FROM w)"]
    for r in range(1, k + 1):
        taken = " UNION ALL ".join(f"SELECT f FROM r{x}" for x in range(1, r)) or "SELECT ''"
        parts.append(f"r{r} AS MATERIALIZED (SELECT f, sum(m * (n - m))::BIGINT AS g FROM (SELECT f, c, count(*) AS m FROM l JOIN k{r - 1} USING (uid) WHERE f NOT IN ({taken}) GROUP BY ALL) JOIN (SELECT c, count(*) AS n FROM k{r - 1} GROUP BY c) USING (c) GROUP BY f ORDER BY g DESC, f LIMIT 1)")
        parts.append(f"k{r} AS MATERIALIZED (SELECT uid, c * 2 + (uid IN (SELECT uid FROM l WHERE f = (SELECT f FROM r{r})))::INT AS c FROM k{r - 1})")
    rows = " UNION ALL ".join(f"SELECT {r}::INT AS round, f AS col, g AS gain FROM r{r}" for r in range(1, k + 1))
    return f"WITH {', '.join(parts)} SELECT round, col, gain, sum(gain) OVER (ORDER BY round)::BIGINT AS total FROM ({rows})"


def row_sample(df: DataFrame, rows: int, n: int, seed: int = 1) -> DataFrame:
    """The users of the smallest hashes, whole: a linear sketch that selects rows. A threshold on the hash first, so only
    about twice the rows are sorted."""
    h = poly4(F.pmod("uid", F.lit(PRIME)), Seed.of(seed, 60))
    near = df.withColumn("h", h).where(F.col("h") < int(min(1.0, (2 * rows + 50) / max(1, n)) * PRIME) + 1)
    return near.orderBy("h", "uid").limit(rows).drop("h")


def row_sample_sql(w: Wide, rows: int, seed: int = 1) -> str:
    return f"SELECT * FROM ({w.sql}) ORDER BY {Seed.of(seed, 60).sql('uid')}, uid LIMIT {rows}"


def local_onehot(codes: np.ndarray, names: list[str], k: int) -> list[tuple[int, str, int, int]]:
    """Class refinement on a sample in memory: codes holds 0/1 columns of one-hot features."""
    n, d = codes.shape
    cls, open_, out, total = np.zeros(n, np.int64), np.ones(d, bool), [], 0
    for r in range(1, min(k, d) + 1):
        _, cls = np.unique(cls, return_inverse=True)
        order = np.argsort(cls, kind="stable")
        first = np.flatnonzero(np.diff(np.concatenate(([-1], cls[order]))))
        m = np.add.reduceat(codes[order].astype(np.int64), first, axis=0)
        size = np.diff(np.append(first, n))[:, None]
        gains = (m * (size - m)).sum(0)
        best = int(np.argmax(np.where(open_, gains, -1)))
        open_[best] = False
        total += int(gains[best])
        out.append((r, names[best], int(gains[best]), total))
        cls = cls * 2 + codes[:, best]
    return out


def select_rowhash(w: Wide, k: int, rows: int, seed: int = 1, n: int | None = None) -> DataFrame:
    """Greedy one-hot features on the row sample: round, col, gain and total in the sample, in one Arrow group."""
    n = n if n is not None else w.df.count()
    long = w.over(row_sample(w.df, rows, n, seed)).long()

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        names = sorted(pdf["f"].unique())
        users, u = np.unique(pdf["uid"].to_numpy(), return_inverse=True)
        codes = np.zeros((len(users), len(names)), np.int8)
        codes[u, np.searchsorted(names, pdf["f"].to_numpy().astype(str))] = 1
        return pd.DataFrame(local_onehot(codes, names, k), columns=["round", "col", "gain", "total"])

    return long.groupBy().applyInPandas(run, "round int, col string, gain long, total long")


def local_codes(columns: list[np.ndarray], values: list[np.ndarray], k: int) -> list[tuple[int, int]]:
    """Class refinement on a sample in memory: columns hold places in each attribute's values, len(values) for none; picks are (attribute,
    place). As local_onehot on the one-hot columns in this order, but an attribute is one count by class, and one whose features
    gained less before than the best of this round is not counted."""
    n = len(columns[0])
    cls, size = np.zeros(n, np.int64), np.array([n], np.int64)
    bounds = [np.full(len(v), n * n // 4 + 1, np.int64) for v in values]
    out: list[tuple[int, int]] = []

    def gains(a: int) -> np.ndarray:
        width = len(values[a]) + 1
        key = cls * width + columns[a]
        if len(size) * width <= max(1 << 20, 2 * n):
            m = np.bincount(key, minlength=len(size) * width).reshape(len(size), width)
            return (m * (size[:, None] - m)).sum(0)[:-1]
        key, m = np.unique(key, return_counts=True)
        got = np.zeros(width, np.int64)
        np.add.at(got, key % width, m * (size[key // width] - m))
        return got[:-1]

    for _ in range(min(k, sum(map(len, values)))):
        best = (-1, 0, 0)  # gain, -attribute, -place
        for a in sorted((a for a in range(len(values)) if len(values[a])), key=lambda a: (-bounds[a].max(), a)):
            if bounds[a].max() < max(0, best[0]):
                break
            bounds[a] = np.where(bounds[a] < 0, -1, gains(a))
            p = int(np.argmax(bounds[a]))
            best = max(best, (int(bounds[a][p]), -a, -p))
        a, p = -best[1], -best[2]
        out.append((a, p))
        bounds[a][p] = -1
        cls = cls * 2 + (columns[a] == p)
        both = np.bincount(cls, minlength=2 * len(size))
        used = both > 0
        cls, size = (np.cumsum(used) - 1)[cls], both[used]
    return out


def packing(c: Codes) -> list[list[tuple[int, int, int]]]:
    """Attributes that share one long each, as (place, least code, number of codes and none); a code range past 2^62 has its own."""
    ends = c.df.agg(*(f(a).alias(f"{x}{i}") for i, a in enumerate(c.attributes) for x, f in (("lo", F.min), ("hi", F.max)))).first()
    words, room = [], 0
    for i in range(len(c.attributes)):
        lo, hi = (0, -1) if ends[f"lo{i}"] is None else (int(ends[f"lo{i}"]), int(ends[f"hi{i}"]))
        width = hi - lo + 2
        if not words or room * width >= 1 << 62:
            words.append([])
            room = 1
        words[-1].append((i, lo, width))
        room *= width
    return words


def packed_word(c: Codes, word: list[tuple[int, int, int]]) -> Column:
    if len(word) == 1:  # none is the least long
        return F.coalesce(F.col(c.attributes[word[0][0]]).cast("long"), F.lit(-(1 << 63)).cast("long"))
    out = F.lit(0).cast("long")
    for i, lo, width in word:
        out = out * width + F.coalesce(F.col(c.attributes[i]) - lo + 1, F.lit(0))
    return out


def unpacked(words: list[list[tuple[int, int, int]]], data: list[np.ndarray]) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Columns and values as local_codes takes them, attributes in order."""
    found = {}
    for word, x in zip(words, data, strict=True):
        for i, lo, width in reversed(word):
            if len(word) == 1:
                codes, at = np.unique(x, return_inverse=True)
                none = codes[:1] == -(1 << 63)
                values, at = (codes[1:], np.where(at == 0, len(codes) - 1, at - 1)) if none.any() else (codes, at)
            else:
                x, part = np.divmod(x, width)
                codes, at = np.unique(part, return_inverse=True) if width > 4 * len(part) + 1024 else _dense(part, width)
                values, at = (codes[1:] + lo - 1, np.where(at == 0, len(codes) - 1, at - 1)) if len(codes) and codes[0] == 0 else (codes + lo - 1, at)
            found[i] = at.astype(np.min_scalar_type(len(values))), values
    return [found[i][0] for i in sorted(found)], [found[i][1] for i in sorted(found)]


def _dense(x: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    used = np.bincount(x, minlength=width) > 0
    return np.flatnonzero(used), (np.cumsum(used) - 1)[x]


def sample_ends(near: DataFrame, sizes: list[int], limit: int, most: int) -> DataFrame:
    """seed, and for each size the last hash and uid (h0, u0, ...) of the seed's users in it; near: seed, h below limit, uid. Hashes are
    counted in bins, and only the bins where a sample ends are sorted."""
    shift = max(0, (limit * 512 // (2 * most + 50)).bit_length() - 1)
    bins = near.groupBy("seed", F.shiftright("h", shift).alias("bin")).agg(F.count("*").alias("n"))
    upto = bins.withColumn("upto", F.sum("n").over(Window.partitionBy("seed").orderBy("bin")))
    ends = {}
    for r in upto.where(F.exists(F.array(*map(F.lit, sizes)), lambda s: (F.col("upto") >= s) & (F.col("upto") - F.col("n") < s))).collect():
        ends[r["seed"], r["bin"]] = r["upto"] - r["n"]
    keys = [s << 31 | b for s, b in ends]
    inside: dict[tuple[int, int], list[tuple[int, int]]] = {}
    for r in near.where((F.shiftleft(F.col("seed").cast("long"), 31) + F.shiftright("h", shift)).isin(keys)).select("seed", "h", "uid").collect() if keys else ():
        inside.setdefault((r["seed"], r["h"] >> shift), []).append((r["h"], r["uid"]))
    found = {}
    for (seed, b), users in inside.items():
        users.sort()
        for i, s in enumerate(sizes):
            if 0 < s - ends[seed, b] <= len(users):
                found[seed, i] = users[s - ends[seed, b] - 1]
    every = (1 << 62, (1 << 63) - 1)  # fewer users than the size: all
    seeds = [r[0] for r in bins.select("seed").distinct().collect()]
    return near.sparkSession.createDataFrame([(seed, *(x for i in range(len(sizes)) for x in found.get((seed, i), every))) for seed in seeds], ", ".join(["seed int", *(f"h{i} long, u{i} long" for i in range(len(sizes)))]))


def sweep_rowhash(c: Codes, k: int, sizes: list[int], seeds: int, n: int) -> DataFrame:
    """sample_rows, seed and picks (array of attribute place and code, in order): one job for all samples, since a smaller
    sample of a seed is the beginning of a larger one. One Arrow group a seed, of the largest sample's users; a user is the size of
    the first sample that holds it and its codes, packed into as few longs as they take, so that no table of all columns is
    written for every seed."""
    most, ordered, words = max(sizes), sorted(set(sizes)), packing(c)
    small = np.min_scalar_type(len(ordered))
    limit = int(min(1.0, (2 * most + 50) / max(1, n)) * PRIME) + 1
    spread = F.explode(F.array(*(F.struct(F.lit(s).alias("seed"), poly4(F.pmod("uid", F.lit(PRIME)), Seed.of(s, 60)).alias("h")) for s in range(1, seeds + 1))))
    near = lambda *more: c.df.select("uid", *more, spread.alias("x")).where(F.col("x.h") < limit).select("x.seed", "x.h", "uid", *(f"w{i}" for i in range(len(more))))
    ends = sample_ends(near(), ordered, limit, most)
    level = F.coalesce(*(F.when((F.col("h") < F.col(f"h{i}")) | (F.col("h") == F.col(f"h{i}")) & (F.col("uid") <= F.col(f"u{i}")), F.lit(i)) for i in range(len(ordered))))
    users = near(*(packed_word(c, x).alias(f"w{i}") for i, x in enumerate(words))).join(F.broadcast(ends), "seed")
    chosen = users.select("seed", level.alias("level"), *(f"w{i}" for i in range(len(words)))).where(F.col("level").isNotNull())

    def pack(batches):
        held: dict[int, list[list[np.ndarray]]] = {}

        def row(seed: int) -> pa.RecordBatch:
            parts = held.pop(seed)
            level, *data = (np.concatenate(x) for x in zip(*parts, strict=True))
            return pa.RecordBatch.from_pylist([{"seed": seed, "level": level.astype(small).tobytes(), "codes": b"".join(x.tobytes() for x in data)}], pa.schema([("seed", pa.int32()), ("level", pa.binary()), ("codes", pa.binary())]))

        for batch in batches:
            columns = [x.to_numpy() for x in batch.columns]
            for seed in np.unique(columns[0]).tolist():
                held.setdefault(seed, []).append([x[columns[0] == seed] for x in columns[1:]])
                if sum(len(x[0]) for x in held[seed]) >= 1 << 18:
                    yield row(seed)
        for seed in list(held):
            yield row(seed)

    def run(t: pa.Table) -> pa.Table:
        levels = np.concatenate([np.frombuffer(x.as_py(), small) for x in t["level"]])
        data = np.concatenate([np.frombuffer(x.as_py(), np.int64).reshape(len(words), -1) for x in t["codes"]], axis=1)
        out = []
        for size in sizes:
            inside = levels <= ordered.index(size)
            columns, values = unpacked(words, list(data[:, inside]))
            out.append({"sample_rows": size, "seed": t["seed"][0].as_py(), "picks": [{"a": a, "v": int(values[a][p])} for a, p in local_codes(columns, values, k)]})
        kind = pa.schema([("sample_rows", pa.int32()), ("seed", pa.int32()), ("picks", pa.list_(pa.struct([("a", pa.int32()), ("v", pa.int64())])))])
        return pa.Table.from_pylist(out, kind)

    packed = chosen.mapInArrow(pack, "seed int, level binary, codes binary")
    return packed.groupBy("seed").applyInArrow(run, "sample_rows int, seed int, picks array<struct<a:int,v:long>>")


def prefix_pairs(c: Codes, runs: list[tuple[int, list[tuple[int, int]]]]) -> DataFrame:
    """run, k and the pairs of users that the first k features of each run separate. The users are counted once by the bits of all
    features that some run has; runs and prefixes are sums of these counts."""
    features = list(dict.fromkeys(p for _, picks in runs for p in picks))
    place = {f: divmod(i, 62) for i, f in enumerate(features)}
    words = [F.lit(0).cast("long")] * (1 + (len(features) - 1) // 62)
    for (a, v), (word, bit) in place.items():
        words[word] = words[word] + F.when(F.col(c.attributes[a]) == v, F.lit(1 << bit).cast("long")).otherwise(F.lit(0))
    names = [f"b{i}" for i in range(len(words))]
    counted = c.df.select(*(x.alias(b) for x, b in zip(words, names, strict=True))).groupBy(*names).agg(F.count("*").alias("n"))

    chosen = [(run, [place[p] for p in picks]) for run, picks in runs]

    def classes_of(batches):
        def add_up(parts: list[pa.RecordBatch]):
            *masks, n = (np.concatenate([b.column(i).to_numpy() for b in parts]) for i in range(len(names) + 1))
            for run, bits in chosen:
                cls = np.zeros(len(n), np.int64)
                for word, bit in bits:
                    cls = cls * 2 + (masks[word] >> bit & 1)
                found, at = np.unique(cls, return_inverse=True)
                f = np.zeros(len(found), np.int64)
                np.add.at(f, at, n)
                every = np.ones(len(found), np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(every * run), pa.array(every * len(bits)), pa.array(found), pa.array(f)], ["run", "most", "cls", "f"])

        held: list[pa.RecordBatch] = []
        for batch in batches:
            held.append(batch)
            if sum(b.num_rows for b in held) >= 1 << 18:
                yield from add_up(held)
                held = []
        if held:
            yield from add_up(held)

    classes = counted.mapInArrow(classes_of, "run int, most int, cls long, f long").groupBy("run", "most", "cls").agg(F.sum("f").alias("f"))
    prefixes = classes.select("run", "f", F.explode(F.transform(F.sequence(F.lit(1), F.col("most")), lambda k: F.struct(k.alias("k"), F.call_function("shiftright", F.col("cls"), F.col("most") - k).alias("cls")))).alias("p"))
    f = prefixes.groupBy("run", "p.k", "p.cls").agg(F.sum("f").alias("f"))
    n2, squares = F.sum("f").cast("decimal(38,0)"), F.sum(F.col("f").cast("decimal(19,0)") * F.col("f").cast("decimal(19,0)"))
    return f.groupBy("run", "k").agg(((n2 * n2 - squares) / 2).cast("long").alias("separated"))


def onehot_pairs(w: Wide, cols: list[str]) -> DataFrame:
    """Pairs that a set of one-hot features separates on all users."""
    bits = [(w.feature(f.split(":", 1)[1].split("=", 1)[0], F.col(f.split(":", 1)[1].split("=", 1)[0])) == f).cast("int").alias(f"b{i}") for i, f in enumerate(cols)]
    return separated_pairs(w.df.select(*bits), [f"b{i}" for i in range(len(cols))])


def estimated_pairs(wide: DataFrame, cols: list[str], n: int, samples: int = 1250, seed: int = 1) -> DataFrame:
    """Pairs separated by raw columns, from the moment complement of their random combination; half of n^2 - F_2."""
    from .combine import column_values

    vector = wide.select("uid", (column_values(wide, cols, seed)).alias("x"))
    return complement_of_sample(vector, n, 2, samples, seed).select((F.col("complement") / 2).alias("separated"), "branch")
