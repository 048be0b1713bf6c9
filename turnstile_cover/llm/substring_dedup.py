"""Removal of long repeated word spans by compaction of a De Bruijn graph.

The graph's nodes are the windows of ``window`` words, its edges the runs of one word more that join two
of them in a text. Windows travel in runs that share the smallest hash of a shorter gram (the anchor), only
for anchors that two documents have, and equal runs of many documents collapse to one row first. Then

* windows are grouped: the first source and its place, and whether all texts agree on the word before and after (degrees);
* a join takes that back to the runs, which fall into fragments: consecutive windows, at consecutive places
  of one source, with no branching node between them;
* fragments that go on in the next run, without a branch, join to whole nonbranching paths along the source's places;
* a document's fragments of one path are one span. The words of each span are compared, by a digest of the texts,
  with those at the source's coordinates, and only then removed.

Without a branch between them, windows that are neighbours at the source are so in every text that has them both, so a
span's coordinates hold even where several texts stand under one id.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from . import bitfilter
from .store import materialize
from .textkit import U, Chunk, chunks, covered, mix, ngram_hash, powers

GRAM = 10
LONGEST = 64
_PATH = U(0x8CB92BA72F3D8DD7)


def sliding_min(x: np.ndarray, n: int) -> np.ndarray:
    """Minimum of each run of n entries, by doubling."""
    span, out = 1, x
    while 2 * span <= n:
        out = np.minimum(out[:-span], out[span:])
        span *= 2
    return out if span == n else np.minimum(out[: len(x) - n + 1], out[n - span : n - span + len(x) - n + 1])


def paths(c: Chunk, window: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Word hashes, and of each compacted path: anchor, first edge, number of edges."""
    c.words()
    hashes = c.word_hash()
    none = np.empty(0, np.int64)
    if len(hashes) < window:
        return hashes, np.empty(0, U), none, none
    gram = min(GRAM, window)
    low = sliding_min(ngram_hash(hashes, gram), window - gram + 1)
    ok = c.window_ok(window)
    new = ok.copy()
    new[1:] &= (low[1:] != low[:-1]) | ~ok[:-1]
    first = np.flatnonzero(new)
    stop = np.flatnonzero(ok & ~np.append(ok[1:] & ~new[1:], False)) + 1
    size = stop - first
    if len(size) and size.max() > LONGEST:  # periodic text: cut, edges still meet by anchor
        parts = -(-size // LONGEST)
        k = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
        first, stop = np.repeat(first, parts) + k * LONGEST, np.repeat(stop, parts)
        size = np.minimum(stop - first, LONGEST)
    return hashes, low[first], first, size


def low(x: Column) -> Column:
    return x.bitwiseAND(0xFFFFFFFF)


def beside(before: Column, after: Column) -> Column:
    """Two neighbours of a window, 32 bits each."""
    return F.shiftleft(before, 32).bitwiseOR(after)


def fragments(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Each run's windows with a source (code: place, one way in, one way out), as fragments without a branch."""
    for batch in batches:
        found = batch.column("found")
        row = np.repeat(np.arange(batch.num_rows), found.value_lengths().to_numpy())
        code, origin, pos = (x.to_numpy(zero_copy_only=False) for x in found.flatten().flatten())
        order = np.lexsort((code, row))
        row, code, origin, pos = row[order], code[order].astype(np.int64), origin[order], pos[order].astype(np.int64)
        i, into, out = code >> 2, code >> 1 & 1, code & 1
        new = np.ones(len(row), bool)
        new[1:] = (row[1:] != row[:-1]) | (i[1:] != i[:-1] + 1) | (origin[1:] != origin[:-1]) | (pos[1:] != pos[:-1] + 1) | (into[1:] & out[:-1] == 0)
        first = np.flatnonzero(new)
        stop = np.append(first[1:], len(row))[: len(first)]
        runs = [batch.column(x).take(pa.array(row[first])) for x in ("anchor", "path")]
        columns = [*runs, pa.array(i[first]), pa.array(stop - first), pa.array(origin[first]), pa.array(pos[first]), pa.array(into[first] == 1), pa.array(out[stop - 1] == 1)]
        yield pa.RecordBatch.from_arrays(columns, ["anchor", "path", "i", "n", "origin", "pos", "into", "out"])


def joined_paths(pieces: DataFrame) -> DataFrame:
    """origin, pos, n of each fragment and the place where its nonbranching path starts in the source."""
    along = Window.partitionBy("origin").orderBy("pos", "n")
    till = F.max(F.struct((F.col("pos") + F.col("n")).alias("end"), "out")).over(along.rowsBetween(Window.unboundedPreceding, -1))
    ends = pieces.groupBy("origin", "pos", "n").agg(F.first("into").alias("into"), F.first("out").alias("out")).withColumn("till", till)
    goes_on = (F.col("pos") < F.col("till.end")) | ((F.col("pos") == F.col("till.end")) & F.col("into") & F.col("till.out"))
    start = F.when(~F.coalesce(goes_on, F.lit(False)), F.col("pos"))
    return ends.select("origin", "pos", "n", F.last(start, ignorenulls=True).over(along).alias("path_pos"))


def whole_spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A document's fragments that follow each other on one path, as one span."""
    for batch in batches:
        found = batch.column("found")
        row = np.repeat(np.arange(batch.num_rows), found.value_lengths().to_numpy())
        start, n, origin, pos, path = (x.to_numpy(zero_copy_only=False).astype(np.int64) for x in found.flatten().flatten())
        order = np.lexsort((start, row))
        row, start, n, origin, pos, path = (x[order] for x in (row, start, n, origin, pos, path))
        new = np.ones(len(row), bool)
        new[1:] = (row[1:] != row[:-1]) | (start[1:] != start[:-1] + n[:-1]) | (origin[1:] != origin[:-1]) | (pos[1:] != pos[:-1] + n[:-1]) | (path[1:] != path[:-1])
        first = np.flatnonzero(new)
        size = np.add.reduceat(n, first) if len(first) else n
        runs = [batch.column(x).take(pa.array(row[first])) for x in ("doc_id", "th")]
        yield pa.RecordBatch.from_arrays([*runs, *(pa.array(x) for x in (start[first], size, origin[first], pos[first]))], ["doc_id", "th", "start", "n", "origin", "pos"])


def repeated_spans(documents: DataFrame, window: int = 50) -> DataFrame:
    """doc_id, text key, start and number of windows, and the source's id and place: spans that also lie in a document of a smaller id."""
    source = documents.select(F.col("doc_id").cast("long").alias("doc_id"), bitfilter.text_key().alias("th"), "text").where(F.col("doc_id").isNotNull() & F.col("text").isNotNull())

    def anchors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            for c in chunks(batch.column("text")):
                _, low, first, _ = paths(c, window)
                docs = ids[c.first + np.searchsorted(c.at, first, "right") - 1]
                yield pa.RecordBatch.from_arrays([pa.array(low.view(np.int64)), pa.array(docs, pa.int64())], ["anchor", "doc_id"])

    found = source.select("doc_id", "text").mapInArrow(anchors, "anchor long, doc_id long").groupBy("anchor").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).where("lo < hi").select("anchor")
    shared_anchors = materialize(found, "dedup-anchors")
    wanted = documents.sparkSession.sparkContext.broadcast(bitfilter.build(shared_anchors, "anchor"))

    def compact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, keys = (batch.column(x).to_numpy(zero_copy_only=False) for x in ("doc_id", "th"))
            for c in chunks(batch.column("text")):
                hashes, low, first, size = paths(c, window)
                some = wanted.value.holds(low) if len(low) else np.zeros(0, bool)
                if not some.any():
                    continue
                low, first, size = low[some], first[some], size[some]
                windows, ok = ngram_hash(hashes, window), c.window_ok(window)
                before, after = np.maximum(first - 1, 0), np.minimum(first + size, len(windows) - 1)
                none = [~ok[before] | (first == 0), ~ok[after] | (first + size == len(windows))]  # no window before or after in the text
                near = [pa.array((windows[at] & U(0xFFFFFFFF)).view(np.int64), mask=m) for at, m in zip((before, after), none, strict=True)]
                up, down = powers(_PATH, len(hashes) + 1)
                total = np.concatenate(([U(0)], np.cumsum(hashes * up[: len(hashes)])))
                name = mix((total[first + size + window - 1] - total[first]) * down[first] + size.astype(U))
                cut = np.concatenate(([0], np.cumsum(size)))
                inside = np.arange(cut[-1]) - np.repeat(cut[:-1], size) + np.repeat(first, size)
                doc = np.searchsorted(c.at, first, "right") - 1
                columns = [pa.array(low.view(np.int64)), pa.array(name.view(np.int64)), pa.array(ids[c.first + doc], pa.int64()), pa.array(keys[c.first + doc], pa.int64()), pa.array((first - c.at[doc]).astype(np.int32)), pa.ListArray.from_arrays(pa.array(cut, pa.int32()), pa.array(windows[inside].view(np.int64))), *near]
                yield pa.RecordBatch.from_arrays(columns, ["anchor", "path", "doc_id", "th", "start", "windows", "before", "after"])

    fields = "anchor long, path long, doc_id long, th long, start int, windows array<long>, before long, after long"
    placed = materialize(source.mapInArrow(compact, fields).join(shared_anchors, "anchor", "left_semi"), "dedup-paths")
    # one row for each different run: its first source, and its neighbours, which agree where all bits are in both aggregates
    every, some = (beside(*(F.coalesce(x, F.lit(none)) for x in ("before", "after"))) for none in (0xFFFFFFFF, 0))
    run = placed.groupBy("anchor", "path").agg(F.min("doc_id").alias("source"), F.min_by("start", "doc_id").alias("at"), F.max("doc_id").alias("latest"), F.first("windows").alias("windows"), F.bit_and(every).alias("every"), F.bit_or(some).alias("some"))
    run = materialize(run, "dedup-distinct")

    def node(w: Column, i: Column) -> Column:
        before, after = (low(F.get("windows", i + x)) for x in (-1, 1))
        sides = [beside(F.coalesce(before, F.shiftrightunsigned(x, 32)), F.coalesce(after, low(F.col(x)))).alias(x) for x in ("every", "some")]
        return F.struct(w.alias("node"), i.alias("i"), *sides)

    nodes = run.select("anchor", "latest", "source", "at", F.inline(F.transform("windows", node))).withColumn("at", F.col("at") + F.col("i"))
    merged = nodes.groupBy("anchor", "node").agg(F.min("source").alias("origin"), F.min_by("at", "source").alias("pos"), F.max("latest").alias("last"), F.bit_and("every").alias("every"), F.bit_or("some").alias("some")).where("origin < last")
    one = [(x == y).cast("int") for x, y in ((F.shiftrightunsigned("every", 32), F.shiftrightunsigned("some", 32)), (low(F.col("every")), low(F.col("some"))))]
    merged = materialize(merged.select("anchor", "node", "origin", "pos", (one[0] * 2 + one[1]).alias("ways")), "dedup-nodes")
    places = run.select("anchor", "path", "latest", F.posexplode("windows").alias("i", "node")).join(merged, ["anchor", "node"]).where("origin < latest")
    places = places.groupBy("anchor", "path").agg(F.collect_list(F.struct((F.col("i") * 4 + F.col("ways")).alias("code"), "origin", "pos")).alias("found"))
    pieces = materialize(places.mapInArrow(fragments, "anchor long, path long, i long, n long, origin long, pos long, into boolean, out boolean"), "dedup-fragments")
    pieces = materialize(pieces.join(joined_paths(pieces), ["origin", "pos", "n"]).select("anchor", "path", "i", "n", "origin", "pos", "path_pos"), "dedup-nonbranching")
    spans = placed.select("anchor", "path", "doc_id", "th", "start").join(pieces, ["anchor", "path"]).where("origin < doc_id")
    spans = spans.groupBy("doc_id", "th").agg(F.collect_list(F.struct((F.col("start") + F.col("i")).alias("start"), "n", "origin", "pos", "path_pos")).alias("found"))
    return spans.mapInArrow(whole_spans, "doc_id long, th long, start long, n long, origin long, pos long")


def remove_repeats(documents: DataFrame, window: int = 50, keep: tuple[str, ...] = ()) -> DataFrame:
    """Per row: doc_id, columns of keep, n_words, n_removed and kept (the kept words, joined by one space).

    A null text has no words. A row with a null id is compared with nothing. Repeated rows of one id are one
    document: neither is the smaller, and a text of its own under the same id keeps its own spans. Where a source
    holds a window at several places, any of them is its coordinate. A very long text has as many spans as it
    has paths. A span whose digest is not its source's, which takes equal hashes of different words, stays.
    """
    spans = materialize(repeated_spans(documents, window), "dedup-spans")
    own = spans.groupBy(F.col("doc_id").alias("id_")).agg(F.collect_list(F.struct("th", "start", "n", "origin", "pos")).alias("spans"))
    asked = spans.select(F.col("origin").alias("id_"), "pos", "n").distinct().groupBy("id_").agg(F.collect_list(F.struct("pos", "n")).alias("asked"))
    needed = materialize(own.join(asked, "id_", "full"), "dedup-needed")
    touched = documents.sparkSession.sparkContext.broadcast(bitfilter.build(needed.select(F.xxhash64("id_").alias("k")), "k"))
    carried = list(dict.fromkeys(("doc_id", *keep)))
    source = documents.select(*dict.fromkeys((*carried, "text")))
    named = source.select(*(F.col(x).alias(f"c{i}_") for i, x in enumerate(carried)), F.col("text").alias("text_"), F.col("doc_id").cast("long").alias("id_"), bitfilter.text_key().alias("th_"))
    named = named.withColumn("k_", F.xxhash64("id_"))
    held = [f"c{i}_" for i in range(len(carried))]
    held_fields = ", ".join(f"c{i}_ {x.dataType.simpleString()}" for i, x in enumerate(source.select(*carried).schema))
    result = f"{held_fields}, n_words long, n_removed long, kept string"

    def parts(batches: Iterator[pa.RecordBatch], open_: bool) -> Iterator[pa.RecordBatch]:
        """Rows that may have or be a source (open), or the others, some at a time."""
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                yield part.filter(pa.array(touched.value.holds(part.column("k_").to_numpy(zero_copy_only=False)) == open_))

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in parts(batches, False):
            n, kept = [], []
            for t in part.column("text_").to_pylist():
                words = (t or "").encode().split()
                n.append(len(words))
                kept.append(b" ".join(words).decode())
            yield pa.RecordBatch.from_arrays([*(part.column(x) for x in held), pa.array(n, pa.int64()), pa.array(np.zeros(len(n), np.int64)), pa.array(kept, pa.string())], [*held, "n_words", "n_removed", "kept"])

    def digests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Digests of the words of a text's spans (with the source's id and place) and of those asked of it (with its own)."""
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                rows = batch.slice(at, 256).to_pylist()
                out: list[tuple] = []
                for r in rows:
                    words = (r["text_"] or "").encode().split()
                    wanted = [(r["id_"], r["th_"], x["start"], x["n"], x["origin"], x["pos"]) for x in r["spans"] or () if x["th"] == r["th_"]]
                    wanted += [(r["id_"], None, x["pos"], x["n"], r["id_"], x["pos"]) for x in r["asked"] or ()]
                    out += [(*x, blake2b(b" ".join(words[x[2] : x[2] + x[3] + window - 1]), digest_size=16).digest()) for x in wanted]
                columns = list(zip(*out, strict=True)) if out else [()] * 7
                types = [*[pa.int64()] * 6, pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(columns, types, strict=True)], ["id_", "th_", "start", "n", "origin", "pos", "digest"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 1024):
                part = batch.slice(at, 1024)
                n, removed, kept = [], [], []
                for t, th, found, bad in zip(*(part.column(x).to_pylist() for x in ("text_", "th_", "spans", "bad")), strict=True):
                    words = (t or "").encode().split()
                    left = {(x["start"], x["n"]) for x in bad or ()}
                    gone = [(x["start"], x["n"] + window - 1) for x in found or () if x["th"] == th and (x["start"], x["n"]) not in left]
                    starts, sizes = np.array(gone, np.int64).reshape(-1, 2).T
                    off = covered(starts, sizes, len(words))
                    n.append(len(words))
                    removed.append(int(off.sum()))
                    kept.append(b" ".join(compress(words, (~off).tolist())).decode())
                yield pa.RecordBatch.from_arrays([*(part.column(x) for x in held), pa.array(n, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.string())], [*held, "n_words", "n_removed", "kept"])

    texts = named.mapInArrow(lambda batches: parts(batches, True), named.schema).drop("k_")
    open_ = materialize(texts.join(needed, "id_", "left"), "dedup-open")
    compared = materialize(open_.select("id_", "th_", "text_", "spans", "asked").mapInArrow(digests, "id_ long, th_ long, start long, n long, origin long, pos long, digest binary"), "dedup-digests")
    at_source = compared.where("th_ is null").select("origin", "pos", "n", "digest")
    unlike = compared.where("th_ is not null").join(at_source, ["origin", "pos", "n", "digest"], "left_anti")
    unlike = materialize(unlike.groupBy("id_", "th_").agg(F.collect_set(F.struct("start", "n")).alias("bad")), "dedup-unlike")
    out = named.mapInArrow(whole, result).unionByName(open_.join(unlike, ["id_", "th_"], "left").select(*held, "text_", "th_", "spans", "bad").mapInArrow(cut, result))
    return out.select(*(F.col(h).alias(x) for h, x in zip(held, carried, strict=True)), "n_words", "n_removed", "kept")
