"""Exact Jaccard join of word-shingle sets with signature trees.

Equal sets collapse to one. Sets that can link share a segment: hash ranges cut a set into more
segments than a linked pair can differ in, so one non-empty segment is the same in both (sets with
too many empty segments add the shingles of their prefix, which linked sets share likewise). A set with
fewer shared segments than any link needs is left out, so a common line does not make candidates.
Documents that share segments form blocks, found through stars, never through pairs. In a block,
a tree of signature nodes - OR-combined token bitmaps and size ranges - is joined with itself by
dual traversal: node pairs whose largest possible overlap is too small are dropped, and so are those
whose documents are linked already. Survivors are verified on the whole sets; a task returns
links that join components, never pairs. Blocks of many bytes are cut into chunks: first every
chunk with some documents of the whole block, then only documents outside the block's
largest component against the other chunks.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache, partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from . import bitfilter
from .components import connected_components
from .store import mark, materialize, tidy
from .textkit import U, Chunk, chunks, mix, ngram_hash

LEAF, FANOUT = 32, 8
CHUNK_BYTES = 24 << 20
GUIDES = 8
KEY_BITS, MAX_KEY_BITS = 10, 28  # of the bitmap of shared keys: 32 MB at most
KEYS_A_PASS, MAX_PASSES = 1 << 25, 8  # keys whose copies are counted in one shuffle
TEXT_BYTES = 1 << 18  # texts hashed at a time, to keep workers small


def shingle_sets(c: Chunk, k: int) -> Iterator[np.ndarray]:
    """Sorted distinct hashes of each document's k-word shingles; with fewer words the whole sequence is one."""
    c.words()
    words = c.word_hash()
    grams = ngram_hash(words, k)
    for i in range(c.docs):
        lo, hi = c.at[i], c.at[i + 1]
        if hi - lo >= k:
            yield np.unique(grams[lo : hi - k + 1])
        elif hi > lo:
            yield ngram_hash(words[lo:hi], int(hi - lo))
        else:
            yield np.empty(0, U)


@lru_cache(8)
def size_classes(num: int, den: int, reserve: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lower bounds of size classes, and each one's largest difference of a linked pair and number of segments."""
    low = [1]
    while low[-1] < 1 << 40:
        low.append(max(low[-1] + 1, low[-1] * 3 // 2))
    bounds = np.array(low)
    differ = (den - num) * (bounds[1:] - 1) // num
    return bounds, differ, differ + 1 + np.ceil(reserve * differ).astype(np.int64)


def segment_keys(s: np.ndarray, num: int, den: int, reserve: float) -> list[tuple[np.ndarray, int]]:
    """Keys of a set and how many of them any linked set has too, for its size class and, near the class's end, the next one.

    Keys are the non-empty segments. Linked sets differ in at most (den - num) / num of the smaller one's size, so in as
    many segments; the others are equal, and all but the set's empty ones are keys of both. If that promises no key, the
    shingles of the prefix are keys as well, of which linked sets share one.
    """
    n = len(s)
    if not n:
        return []
    bounds, differ, parts = size_classes(num, den, reserve)
    own = int(np.searchsorted(bounds, n, "right")) - 1
    out, mixed = [], mix(s)
    for k in (own, own + 1) if n * den >= num * int(bounds[own + 1]) else (own,):
        p = int(parts[k])
        at = ((s >> U(32)) * U(p)) >> U(32)
        first = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
        size = np.diff(np.append(first, n)).astype(U)
        keys = mix(np.add.reduceat(mixed, first) + mix(at[first] + U(k << 40)) + size)
        if len(first) <= differ[k]:
            keys = np.concatenate((keys, mix(s[: n - -(-num * n // den) + 1] ^ mix(np.array([k + 1], U)))))
        out.append((keys, max(1, len(first) - (den - num) * n // num)))
    return out


def signature(s: np.ndarray, bits: int) -> np.ndarray:
    out = np.zeros(bits, bool)
    out[(s & U(bits - 1)).astype(np.int64)] = True
    return np.packbits(out).view(U)


class SignatureTree:
    """Documents sorted by size under nodes of OR-combined bitmaps and size ranges."""

    def __init__(self, sets: list[np.ndarray], labels: np.ndarray):
        sizes = np.array([len(s) for s in sets])
        lows = np.array([s[0] if len(s) else U(0) for s in sets], U)
        self.order = np.lexsort((lows, sizes))
        self.sets, self.sizes = sets, sizes
        bits = 1 << max(9, min(15, int(4 * sizes.max()).bit_length()))
        self.maps = np.stack([signature(s, bits) for s in sets])
        self.excess = sizes - np.bitwise_count(self.maps).sum(1)
        self.parent = {int(x): int(x) for x in np.unique(labels)}
        self.labels = labels
        level = [self._node(self.order[i : i + LEAF], None) for i in range(0, len(sets), LEAF)]
        while len(level) > 1:
            level = [self._node(None, level[i : i + FANOUT]) for i in range(0, len(level), FANOUT)]
        self.root = level[0]

    def _node(self, docs, children):
        if docs is not None:
            return (np.bitwise_or.reduce(self.maps[docs], axis=0), int(self.sizes[docs].min()), int(self.sizes[docs].max()), int(self.excess[docs].max()), docs, None)
        return (np.bitwise_or.reduce([c[0] for c in children], axis=0), min(c[1] for c in children), max(c[2] for c in children), max(c[3] for c in children), None, children)

    def find(self, x: int) -> int:
        while self.parent[x] != x:
            self.parent[x] = x = self.parent[self.parent[x]]
        return x

    def join(self, num: int, den: int) -> list[tuple[int, int]]:
        """Verified links between documents of different components, one for each merge."""
        links: list[tuple[int, int]] = []
        todo = [(self.root, self.root)]
        while todo:
            x, y = todo.pop()
            if x[1] * den > 0 and (x[2] * den < num * y[1] or y[2] * den < num * x[1]):
                continue  # no sizes close enough
            if x is not y:
                most = min(int(np.bitwise_count(x[0] & y[0]).sum()) + min(x[3], y[3]), x[2], y[2])
                if most * (num + den) < num * (x[1] + y[1]):
                    continue  # the largest possible overlap is too small
            if x[5] is None and y[5] is None:
                self._leaves(x[4], y[4], x is y, num, den, links)
            elif x is y:
                todo += [(a, b) for i, a in enumerate(x[5]) for b in x[5][i:]]
            else:
                todo += [(a, y) for a in x[5]] if x[5] is not None else [(x, b) for b in y[5]]
        return links

    def _leaves(self, a: np.ndarray, b: np.ndarray, same: bool, num: int, den: int, links: list) -> None:
        roots = [np.array([self.find(int(self.labels[i])) for i in d]) for d in (a, b)]
        ok = roots[0][:, None] != roots[1][None, :]
        if same:
            ok &= np.tri(len(a), k=-1, dtype=bool)
        if not ok.any():
            return
        na, nb = self.sizes[a][:, None], self.sizes[b][None, :]
        ma, mb = self.maps[a], self.maps[b]
        both = np.bitwise_count(ma[:, None, :] & mb[None, :, :]).sum(2, dtype=np.int64)
        most = np.minimum(both + self.excess[a][:, None], both + self.excess[b][None, :])
        ok &= most * (num + den) >= num * (na + nb)
        for i, j in zip(*np.nonzero(ok), strict=True):
            i, j = int(a[i]), int(b[j])
            p, q = self.find(int(self.labels[i])), self.find(int(self.labels[j]))
            if p == q:
                continue
            u, v = self.sets[i], self.sets[j]
            common = len(np.intersect1d(u, v, assume_unique=True))
            if common * den >= num * (len(u) + len(v) - common):
                self.parent[max(p, q)] = min(p, q)
                links.append((i, j))


def held_rows(batches: Iterator[pa.RecordBatch], wanted: bitfilter.BitFilter, rows: int = 256) -> Iterator[pa.RecordBatch]:
    """Rows whose key k is wanted, a few at a time: a batch's texts are never copied at once."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            part = batch.slice(at, rows)
            hold = wanted.holds(part.column("k").to_numpy(zero_copy_only=False))
            if hold.any():
                yield part if hold.all() else part.filter(pa.array(hold))


def near_duplicates(documents: DataFrame, words: int = 5, percent: int = 80, reserve: float | None = None) -> DataFrame:
    """Per row: doc_id, text_key, n_shingles and component_id, the smallest id that links reach.

    Links: Jaccard similarity of the sets at least percent / 100, exactly. A text without words, or a null one,
    links with nothing. A row with a null id has no component; repeated ids are one document.
    """
    num, den = percent, 100
    spare = reserve if reserve is not None else 0.05 if percent >= 88 else 0.15
    spark, since = documents.sparkSession, mark()
    source = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")

    def outline(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for c in chunks(batch.column("text"), lower=True, limit=TEXT_BYTES):
                n, one, two = [], [], []
                for s in shingle_sets(c, words):
                    m = mix(s)
                    n.append(len(s))
                    one.append(m.sum(dtype=U))
                    two.append(mix(m ^ U(0x2545F4914F6CDD1D)).sum(dtype=U))
                ids = [batch.column(x).slice(c.first, c.docs) for x in ("doc_id", "text_key")]
                yield pa.RecordBatch.from_arrays([*ids, pa.array(np.array(n, np.int64)), *(pa.array(np.array(x, U).view(np.int64)) for x in (one, two))], ["doc_id", "text_key", "n", "one", "two"])

    keyed = source.select("doc_id", bitfilter.text_key().alias("text_key"), "text")
    outlines = materialize(keyed.mapInArrow(outline, "doc_id long, text_key long, n long, one long, two long"), "join-outlines")
    reps = materialize(outlines.where("n > 0 and doc_id is not null").groupBy("one", "two", "n").agg(F.min("doc_id").alias("rep")), "join-sets")

    # segments that two different sets share, and the star of each; keys are made from the texts each time, never stored
    broadcast = documents.sparkSession.sparkContext.broadcast
    chosen = broadcast(bitfilter.build(reps.select(F.xxhash64("rep").alias("k")), "k"))
    hashed = source.where("doc_id is not null").select("doc_id", F.xxhash64("doc_id").alias("k"), "text")

    def keys_of(batches: Iterator[pa.RecordBatch], shared: bitfilter.BitFilter | None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        for part in held_rows(batches, chosen.value):
            ids = part.column("doc_id").to_numpy(zero_copy_only=False)
            for c in chunks(part.column("text"), lower=True, limit=TEXT_BYTES):
                owner, flat = [], [np.empty(0, U)]
                for doc, s in zip(ids[c.first : c.first + c.docs].tolist(), shingle_sets(c, words), strict=True):
                    for keys, least in segment_keys(s, num, den, spare):
                        keys = keys if shared is None else keys[shared.holds(keys)]
                        if shared is None or len(keys) >= least:  # with fewer shared keys no set can be linked
                            owner.append(np.full(len(keys), doc))
                            flat.append(keys)
                yield np.concatenate([np.empty(0, np.int64), *owner]), np.concatenate(flat)

    # keys are counted a share at a time, so that not all keys of all sets lie in one shuffle
    shingles = int(reps.agg(F.sum("n")).first()[0] or 0)
    passes = min(MAX_PASSES, 1 + shingles // KEYS_A_PASS)

    def all_keys(batches: Iterator[pa.RecordBatch], share: int) -> Iterator[pa.RecordBatch]:
        for _, flat in keys_of(batches, None):
            mine = flat if passes == 1 else flat[mix(flat) % U(passes) == U(share)]
            yield pa.RecordBatch.from_arrays([pa.array(mine.view(np.int64))], ["key"])

    # a repeated row of a representative gives its keys once more, which only makes a key shared that need not be
    heads = None
    for share in range(passes):
        some = hashed.mapInArrow(partial(all_keys, share=share), "key long").groupBy("key").agg(F.count("*").alias("n")).where("n > 1").select("key")
        some = materialize(some, "join-heads")
        heads = some if heads is None else heads.unionByName(some)
        if share + 1 < passes:
            tidy(spark, since, (outlines, reps, heads))
    tidy(spark, since, (outlines, reps, heads))  # every key of every set went through that shuffle
    # ten bits a key: were the bitmap full, most keys of all sets would seem shared
    wanted = broadcast(bitfilter.build(heads, "key", each=KEY_BITS, max_bits=MAX_KEY_BITS, places=4))

    def shared_keys(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for owner, flat in keys_of(batches, wanted.value):
            yield pa.RecordBatch.from_arrays([pa.array(owner, pa.int64()), pa.array(flat.view(np.int64))], ["rep", "key"])

    shared = materialize(hashed.mapInArrow(shared_keys, "rep long, key long"), "join-shared")
    star = shared.groupBy("key").agg(F.min("rep").alias("head"), F.max("rep").alias("last")).where("head < last").select("key", "head")
    star = shared.join(materialize(star, "join-stars"), "key").where("rep <> head").select(F.col("rep").alias("a"), F.col("head").alias("b")).distinct()
    star = materialize(star, "join-star")
    tidy(spark, since, (outlines, reps, star))
    blocks = materialize(connected_components(star).select(F.col("node").alias("rep"), F.col("component").alias("block")), "join-blocks")
    tidy(spark, since, (outlines, reps, blocks))
    members = broadcast(bitfilter.build(blocks.select(F.xxhash64("rep").alias("k")), "k"))

    def load(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in held_rows(batches, members.value):
            for c in chunks(part.column("text"), lower=True, limit=TEXT_BYTES):
                yield pa.RecordBatch.from_arrays([part.column("doc_id").slice(c.first, c.docs), pa.array([s.tobytes() for s in shingle_sets(c, words)], pa.binary())], ["rep", "shingles"])

    loaded = hashed.mapInArrow(load, "rep long, shingles binary")
    sets = materialize(loaded.where(F.length("shingles") > 0).join(blocks, "rep"), "join-members")
    tidy(spark, since, (outlines, reps, blocks, sets))

    totals = sets.groupBy("block").agg(F.sum(F.length("shingles")).alias("bytes"), F.count("*").alias("docs"))
    totals = materialize(totals.select("block", "docs", F.ceil(F.col("bytes") / CHUNK_BYTES).cast("int").alias("n_chunks")), "join-totals")
    tasks = max(1, int((sets.agg(F.sum(F.length("shingles"))).first()[0] or 0) // (CHUNK_BYTES // 4)))
    sized = sets.join(totals, "block")
    small = sized.where("n_chunks = 1").select(F.pmod(F.xxhash64("block"), F.lit(tasks)).alias("task"), "block", F.lit(0).alias("chunk"), "rep", F.col("rep").alias("label"), "shingles")
    links = materialize(tree_links(small, num, den), "join-links")
    large = materialize(sized.where("n_chunks > 1").withColumn("chunk", F.pmod(F.xxhash64("rep"), F.col("n_chunks")).cast("int")), "join-large")
    if not large.isEmpty():
        tidy(spark, since, (outlines, reps, links, large))
        links = large_links(large, links, num, den)

    tidy(spark, since, (outlines, reps, links))
    components = connected_components(links)
    tidy(spark, since, (outlines, reps, components))
    final = outlines.select("doc_id", "text_key", "n", "one", "two").join(reps, ["one", "two", "n"], "left").join(components.withColumnRenamed("node", "rep"), "rep", "left")
    return final.select("doc_id", "text_key", F.col("n").alias("n_shingles"), F.coalesce("component", "rep", "doc_id").alias("component_id"))


def tree_links(rows: DataFrame, num: int, den: int) -> DataFrame:
    """Links (a, b) found by a tree over each block and chunk; rows: task, block, chunk, rep, label, shingles."""

    def grow(t: pa.Table) -> pa.Table:
        t = t.sort_by([("block", "ascending"), ("chunk", "ascending"), ("rep", "ascending")])
        key = t.select(["block", "chunk"]).to_pandas().to_numpy()
        reps, labels, sets = t.column("rep").to_numpy(), t.column("label").to_numpy(), t.column("shingles").to_pylist()
        edge = np.flatnonzero(np.concatenate(([True], (key[1:] != key[:-1]).any(1), [True])))
        out: list[tuple[int, int]] = []
        for lo, hi in zip(edge[:-1], edge[1:], strict=True):
            if hi - lo > 1:
                tree = SignatureTree([np.frombuffer(s, U) for s in sets[lo:hi]], labels[lo:hi])
                out += [(int(reps[lo + i]), int(reps[lo + j])) for i, j in tree.join(num, den)]
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([x for _, x in out], pa.int64())})

    return rows.groupBy("task").applyInArrow(grow, "a long, b long")


def large_links(large: DataFrame, links: DataFrame, num: int, den: int) -> DataFrame:
    """Links of blocks of several chunks: each chunk with the block's guides, then what is not in the largest component with all chunks."""
    task = F.xxhash64("block", "chunk").alias("task")
    place = Window.partitionBy("block").orderBy("rep")
    guides = large.select("block", "rep").withColumn("i", F.row_number().over(place)).where(F.col("i") <= GUIDES).select("block", "rep")
    spread = large.join(guides, ["block", "rep"], "left_semi").select("block", F.explode(F.sequence(F.lit(0), F.col("n_chunks") - 1)).alias("chunk"), "rep", F.col("rep").alias("label"), "shingles", F.col("chunk").alias("home")).where("chunk <> home").drop("home")
    own = large.select("block", "chunk", "rep", F.col("rep").alias("label"), "shingles")
    first = materialize(tree_links(own.unionByName(spread).select(task, "*"), num, den), "join-links")
    links = materialize(links.union(first), "join-links")

    found = materialize(connected_components(links), "join-found").withColumnRenamed("node", "rep")
    labelled = large.join(found, "rep", "left").withColumn("label", F.coalesce("component", "rep"))
    counts = labelled.groupBy("block", "label").count()
    main = counts.groupBy("block").agg(F.max(F.struct("count", "label")).alias("top"), F.count("*").alias("parts")).where("parts > 1").select("block", F.col("top.label").alias("main"))
    open_ = materialize(labelled.join(main, "block"), "join-open")
    rest = open_.where("label <> main")
    # a document outside the main component visits every chunk; there it also meets the visitors of the chunk's own documents
    visits = rest.select("block", F.explode(F.sequence(F.lit(0), F.col("n_chunks") - 1)).alias("chunk"), "rep", "label", "shingles", F.col("chunk").alias("home")).where("chunk <> home").drop("home")
    stay = open_.select("block", "chunk", "rep", "label", "shingles")
    second = materialize(tree_links(stay.unionByName(visits).select(task, "*"), num, den), "join-links")
    return materialize(links.union(second), "join-links")
