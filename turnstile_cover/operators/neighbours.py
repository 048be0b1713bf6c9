"""Coverage of vectors by their neighbours, from blocks of vectors: the entries of the matrix are counted and never become rows."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .checkpoints import cut
from .greedy import trajectory

BLOCK = "p long, ids binary, sizes binary, data binary"
ROWS = 2048

Vectors = tuple[np.ndarray, np.ndarray, np.ndarray]


def packed(vectors: DataFrame, rows: int = ROWS) -> tuple[DataFrame, int, np.dtype]:
    """Blocks of about so many vectors (id, v) by a hash of the id, their number, and the type of their numbers. A vector that is null or
    holds a null is near nothing and left out, as is one without an id."""
    kind = np.dtype("f4" if vectors.schema["v"].dataType.elementType.simpleString() == "float" else "f8")
    blocks = max(4, math.ceil(vectors.count() / rows))
    whole = vectors.where(F.col("id").isNotNull() & F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull()))
    number = F.transform("v", lambda x: x.cast("float" if kind == np.dtype("f4") else "double"))
    placed = whole.select(F.pmod(F.xxhash64("id"), F.lit(blocks)).alias("p"), F.col("id").cast("long").alias("id"), number.alias("v"))

    def pack(t: pa.Table) -> pa.Table:
        ids, lists = t["id"].to_numpy(), t["v"].combine_chunks()
        sizes = np.asarray(lists.value_lengths(), np.int64)
        data = lists.flatten().to_numpy(zero_copy_only=False).astype(kind)
        return pa.table({"p": pa.array([t["p"][0].as_py()], pa.int64()), "ids": [ids.tobytes()], "sizes": [sizes.tobytes()], "data": [data.tobytes()]})

    return cut(placed.groupBy("p").applyInArrow(pack, BLOCK)), blocks, kind


def read(ids: bytes, sizes: bytes, data: bytes, kind: np.dtype) -> Vectors:
    return np.frombuffer(ids, np.int64), np.frombuffer(sizes, np.int64), np.frombuffer(data, kind).astype(np.float64)


def near(x: np.ndarray, y: np.ndarray, at_least: float) -> np.ndarray:
    """Which rows of x and y have at least that cosine. Products of whole matrices decide all pairs but those at the limit, within
    the error of such a product; these are summed in the order of the dimensions."""
    in_order = lambda a: a.cumsum(1)[:, -1] if a.shape[1] else np.zeros(len(a))
    with np.errstate(all="ignore"):
        nx, ny = np.sqrt(in_order(x * x)), np.sqrt(in_order(y * y))
        far = x @ y.T - (at_least * nx)[:, None] * ny
        out = far >= 0
        error = 8 * (x.shape[1] + 4) * np.finfo(float).eps * (nx[:, None] * ny)
        for at in np.array_split(np.flatnonzero(~(np.abs(far) > error)), 1 + far.size // (1 << 16)):
            i, j = np.divmod(at, len(y))
            out[i, j] = ~(in_order(x[i] * y[j]) < at_least * nx[i] * ny[j])  # a number that is none is above all
    return out


def links(a: Vectors, b: Vectors, at_least: float) -> tuple[list[np.ndarray], np.ndarray]:
    """Different ids of a and of b, and which of them have vectors near each other; vectors of other lengths are not."""
    named = []
    out = np.zeros((len(a[0]), len(b[0])), bool)
    for size in np.intersect1d(a[1], b[1]):
        i, j = np.flatnonzero(a[1] == size), np.flatnonzero(b[1] == size)
        out[np.ix_(i, j)] = near(a[2][np.repeat(a[1] == size, a[1])].reshape(len(i), size), b[2][np.repeat(b[1] == size, b[1])].reshape(len(j), size), at_least)
    for axis, ids in ((0, a[0]), (1, b[0])):
        order = np.argsort(ids, kind="stable")
        first = np.flatnonzero(np.append(True, ids[order][1:] != ids[order][:-1]))
        named.append(ids[order][first])
        out = out.take(order, axis)
        if len(first) < len(ids):  # an id with several vectors is near what any of them is near
            out = np.logical_or.reduceat(out, first, axis)
    return named, out


def gains(left: DataFrame, right: DataFrame, kind: np.dtype, at_least: float) -> DataFrame:
    """j and g, the ids of left that are near it, of every id of right. Each pair of blocks is one product of matrices."""
    def run(batches):
        found: dict[int, list[np.ndarray]] = {}
        for batch in batches:
            for r in batch.to_pylist():
                (_, j), near_ = links(read(r["ids"], r["sizes"], r["data"], kind), read(r["ids2"], r["sizes2"], r["data2"], kind), at_least)
                g = near_.sum(0, dtype=np.int64)
                if r["q"] in found:
                    found[r["q"]][1] += g
                else:
                    found[r["q"]] = [j, g]
        for j, g in found.values():
            yield pa.RecordBatch.from_arrays([pa.array(j, pa.int64()), pa.array(g, pa.int64())], ["j", "g"])

    other = right.select(F.col("p").alias("q"), *(F.col(c).alias(f"{c}2") for c in ("ids", "sizes", "data")))
    both = left.hint("shuffle_replicate_nl").crossJoin(other)  # no side is broadcast, and neither goes through a shuffle once more
    return both.mapInArrow(run, "j long, g long").groupBy("j").agg(F.sum("g").alias("g"))


def newly_covered(blocks: DataFrame, kind: np.dtype, picks: list[list[list[float]]], at_least: float) -> DataFrame:
    """Blocks of the ids that are near the last pick and no earlier one."""
    def as_block(vectors: list[list[float]]) -> Vectors:
        return np.zeros(len(vectors), np.int64), np.array([len(v) for v in vectors], np.int64), np.array([x for v in vectors for x in v], np.float64)

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                b = read(r["ids"], r["sizes"], r["data"], kind)
                near_ = []
                for p in picks:
                    (ids, _), hit = links(b, as_block(p), at_least)
                    near_.append(hit[:, 0])
                new = ids[near_[-1] & ~np.any(near_[:-1], axis=0)] if len(near_) > 1 else ids[near_[-1]]
                ids_, sizes, data = take_ids(b, new)
                if len(ids_):
                    yield pa.RecordBatch.from_pylist([{"p": r["p"], "ids": ids_.tobytes(), "sizes": sizes.tobytes(), "data": data.astype(kind).tobytes()}])

    return blocks.mapInArrow(run, BLOCK)


def take_ids(b: Vectors, ids: np.ndarray) -> Vectors:
    keep = np.isin(b[0], ids)
    return b[0][keep], b[1][keep], b[2][np.repeat(keep, b[1])]


def cover(vectors: DataFrame, k: int, at_least: float = 0.2, rows: int = ROWS) -> DataFrame:
    """Greedy maximum coverage of vectors (id, v) by those within a cosine of them: what cover_df gives on the pairs as entries.

    The first round counts every pair; a later one only takes off what the last pick newly covers, so that k rounds cost little more
    than one. Only picks and their vectors reach the driver.
    """
    spark = vectors.sparkSession
    blocks, many, kind = packed(vectors, rows)
    counted = cut(gains(blocks.repartition(many), blocks, kind, at_least))
    picked, near_picks, out, total = [], [], [], 0
    for r in range(1, k + 1):
        left = counted.where(~F.col("j").isin(picked)) if picked else counted
        best = left.groupBy("j").agg(F.sum("g").alias("g")).orderBy(F.desc("g"), "j").limit(1).collect()
        if not best:
            break
        j, gain = best[0]["j"], int(best[0]["g"])
        picked.append(j)
        total += gain
        out.append((r, j, gain, total))
        if r < k and gain:
            near_picks.append([x["v"] for x in vectors.where(F.col("id") == j).collect() if x["v"] is not None and None not in x["v"]])
            fresh = cut(newly_covered(blocks, kind, near_picks, at_least))
            counted = counted.unionByName(cut(gains(fresh.repartition(many), blocks, kind, at_least).select("j", (-F.col("g")).alias("g"))))
    return trajectory(spark, out, "long")
