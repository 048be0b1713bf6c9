"""Benchmark decontamination with a generalised suffix automaton over the words of the test items.

The automaton is built from the items alone, in parts of bounded size, frozen into sorted arrays and
sent to the executors; every document streams through it while the length of the longest match is
tracked. Items of more words than one pass may hold take several passes, whose hits are united. Words that cannot lie in a long enough match are skipped beforehand: each window
consists of short grams, and a bitmap of the items' grams has no false negatives.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .store import materialize
from .textkit import U, Chunk, chunks, ngram_hash

ALNUM = np.zeros(256, bool)
ALNUM[[*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]] = True
FILTER_BITS = 22


@dataclass
class Automaton:
    """Generalised suffix automaton of word sequences; owners: the items in which a state's strings occur."""

    window: int = 10
    step: list[dict[int, int]] = field(default_factory=lambda: [{}])
    link: list[int] = field(default_factory=lambda: [-1])
    size: list[int] = field(default_factory=lambda: [0])
    owners: list[set[int]] = field(default_factory=lambda: [set()])
    whole: dict[int, list[tuple[int, int]]] = field(default_factory=dict)
    shortest: int = 10

    def _state(self, size: int, link: int, step: dict[int, int]) -> int:
        self.step.append(step)
        self.link.append(link)
        self.size.append(size)
        self.owners.append(set())
        return len(self.size) - 1

    def _split(self, p: int, word: int, q: int) -> int:
        twin = self._state(self.size[p] + 1, self.link[q], dict(self.step[q]))
        while p >= 0 and self.step[p].get(word) == q:
            self.step[p][word] = twin
            p = self.link[p]
        self.link[q] = twin
        return twin

    def _extend(self, last: int, word: int) -> int:
        q = self.step[last].get(word)
        if q is not None:  # another item has this string already
            return q if self.size[q] == self.size[last] + 1 else self._split(last, word, q)
        new = self._state(self.size[last] + 1, 0, {})
        p = last
        while p >= 0 and word not in self.step[p]:
            self.step[p][word] = new
            p = self.link[p]
        if p >= 0:
            q = self.step[p][word]
            self.link[new] = q if self.size[q] == self.size[p] + 1 else self._split(p, word, q)
        return new

    @classmethod
    def of(cls, items: list[list[int]], window: int) -> Automaton:
        out = cls(window)
        for words in items:
            state = 0
            for w in words:
                state = out._extend(state, w)
        for i, words in enumerate(items):
            state = 0
            for w in words:
                state = out.step[state][w]
                up = state
                while up > 0 and i not in out.owners[up]:
                    out.owners[up].add(i)
                    up = out.link[up]
            if 0 < len(words) < window:
                out.whole.setdefault(state, []).append((len(words), i))
        out.shortest = min([window, *(len(x) for x in items if x)])
        return out

    def frozen(self) -> Frozen:
        size, keys, ends = len(self.size), [], []
        for state, step in enumerate(self.step):
            keys += [state << 32 | w for w in step]
            ends += step.values()
        at, to = np.array(keys, np.int64), np.array(ends, np.int32)
        order = np.argsort(at)
        flat = lambda lists: np.fromiter((x for one in lists for x in one), np.int32)
        cut = lambda counts: np.concatenate(([0], np.cumsum(np.fromiter(counts, np.int64, size))))
        return Frozen(self.window, self.shortest, at[order], to[order], np.array(self.link, np.int32), np.array(self.size, np.int32), flat(sorted(o) for o in self.owners), cut(len(o) for o in self.owners), self.whole)


@dataclass
class Frozen:
    """An automaton in arrays: a transition's key is its state and word; owners of a state lie between two cuts."""

    window: int
    shortest: int
    keys: np.ndarray
    to: np.ndarray
    link: np.ndarray
    size: np.ndarray
    owner: np.ndarray
    cut: np.ndarray
    whole: dict[int, list[tuple[int, int]]]

    def step(self, state: int, word: int) -> int:
        key = state << 32 | word
        at = int(self.keys.searchsorted(key))
        return int(self.to[at]) if at < len(self.keys) and self.keys[at] == key else 0

    def scan(self, words: list[int]) -> tuple[list[tuple[int, int]], set[int]]:
        """Occurrences (end, length) in a stretch of words, and the items found."""
        found, items = [], set()
        state = length = 0
        for at, w in enumerate(words):
            if w < 0:
                state = length = 0
                continue
            while not (new := self.step(state, w)) and state:
                state = int(self.link[state])
                length = int(self.size[state])
            state = new
            length = length + 1 if state else 0
            if length >= self.shortest:
                up, most = state, length
                while up > 0:
                    if most >= self.window > self.size[self.link[up]]:
                        found.append((at + 1, self.window))
                        items.update(self.owner[self.cut[up] : self.cut[up + 1]].tolist())
                    for n, item in self.whole.get(up, ()):
                        if n <= most:
                            found.append((at + 1, n))
                            items.add(item)
                    up = int(self.link[up])
                    most = int(self.size[up])
        return found, items


@dataclass
class Index:
    """What the executors get: automaton, items' ids, vocabulary (sorted hashes and their numbers) and the filter's bitmaps."""

    automaton: Frozen
    ids: list[str | None]
    vocabulary: np.ndarray
    numbers: np.ndarray
    gram: int
    known: np.ndarray
    grams: np.ndarray

    def look_up(self, hashes: np.ndarray) -> list[int]:
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)
        return np.where(self.vocabulary[at] == hashes, self.numbers[at], -1).tolist()


def build_index(items: list[tuple[object, str | None]], window: int) -> Index:
    column = pa.array([t for _, t in items], pa.large_string())
    vocabulary: dict[int, int] = {}
    sequences: list[list[int]] = []
    hashed: list[np.ndarray] = []
    for c in chunks(column, lower=True):
        c.words(ALNUM)
        h = c.word_hash()
        for i in range(c.docs):
            part = h[c.at[i] : c.at[i + 1]]
            hashed.append(part)
            sequences.append([vocabulary.setdefault(w, len(vocabulary)) for w in part.tolist()])
    automaton = Automaton.of(sequences, window).frozen()
    gram = min(4, automaton.shortest)
    shift = U(64 - FILTER_BITS)
    known, grams = np.zeros(1 << FILTER_BITS, bool), np.zeros(1 << FILTER_BITS, bool)
    for part in hashed:
        known[part >> shift] = True
        if len(part) >= gram:
            grams[ngram_hash(part, gram) >> shift] = True
    words = np.fromiter(vocabulary, U, len(vocabulary))
    order = np.argsort(words)
    return Index(automaton, [None if i is None else str(i) for i, _ in items], words[order], order.astype(np.int64), gram, np.packbits(known), np.packbits(grams))


def item_parts(benchmark: DataFrame, most_chars: int) -> Iterator[list[tuple[object, str | None]]]:
    """Items in order, in parts of at most so many characters (an item alone may be longer)."""
    part, held = [], 0
    for r in benchmark.select("item_id", "text").orderBy("item_id", "text").toLocalIterator():
        n = len(r[1] or "")
        if part and held + n > most_chars:
            yield part
            part, held = [], 0
        part.append((r[0], r[1]))
        held += n
    yield part


def scan_chunk(c: Chunk, index: Index, known: np.ndarray, grams: np.ndarray) -> tuple[np.ndarray, dict[int, set[int]]]:
    """Mask of the chunk's words that are hit, and the items found by document."""
    c.words(ALNUM)
    total, g, auto = len(c.starts), index.gram, index.automaton
    hit, items = np.zeros(total, bool), {}
    shift = U(64 - FILTER_BITS)
    if total < g or not len(index.vocabulary):
        return hit, items
    hashes = c.word_hash()
    seen = known[hashes >> shift]
    ok = c.window_ok(g)
    for k in range(g):
        ok &= seen[k : total - g + 1 + k]
    at = np.flatnonzero(ok)
    ok[at] = grams[ngram_hash(hashes, g)[at] >> shift] if len(at) else False
    edge = np.flatnonzero(np.diff(np.concatenate(([False], ok, [False])).astype(np.int8)))
    for a, b in zip(edge[0::2].tolist(), edge[1::2].tolist(), strict=True):
        if b - a < auto.shortest - g + 1:
            continue
        found, which = auto.scan(index.look_up(hashes[a : b + g - 1]))
        if found:
            for end, n in found:
                hit[a + end - n : a + end] = True
            items.setdefault(int(np.searchsorted(c.at, a, "right")) - 1, set()).update(which)
    return hit, items


def without_hits(c: Chunk, i: int, hit: np.ndarray) -> str:
    """Text of document i of the chunk without its runs of hit words."""
    lo, hi = c.at[i], c.at[i + 1]
    edge = np.flatnonzero(np.diff(np.concatenate(([False], hit[lo:hi], [False])).astype(np.int8)))
    raw, keep, at = c.data.tobytes(), [], int(c.offsets[i])
    for a, b in zip(edge[0::2], edge[1::2], strict=True):
        keep.append(raw[at : int(c.starts[lo + a])])
        at = int(c.ends[lo + b - 1])
    return b"".join([*keep, raw[at : int(c.offsets[i + 1])]]).decode()


def spans_of(hit: np.ndarray, at: np.ndarray) -> list[list[int]]:
    """For each document the runs of its hit words: first, end, first, end, ..."""
    out = []
    for lo, hi in zip(at[:-1], at[1:], strict=True):
        part = hit[lo:hi]
        out.append(np.flatnonzero(np.diff(np.concatenate(([False], part, [False])).astype(np.int8))).tolist() if part.any() else [])
    return out


def decontaminate(documents: DataFrame, benchmark: DataFrame, window: int = 10, part_words: int = 250_000, pass_parts: int = 4, clean: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """Per row: doc_id, columns of keep, n_words, n_hit, items (ids as strings, sorted), and with clean the text without hits.

    A null or empty text has no words, a null or empty item no windows; repeated items count one by one, and an item of a
    null id marks words but is not listed. Repeated rows give the same result. Items of any total length: an automaton
    takes up to part_words words (counted as eight characters each; at the default about 250 MB of driver while it is built,
    25 MB sent), a pass over the documents pass_parts automata. Further passes carry the hit spans of the earlier ones.
    """
    spark = documents.sparkSession
    carried = list(dict.fromkeys(("doc_id", *(k for k in keep if k != "text"))))
    held = [f"c{i}_" for i in range(len(carried))]
    source = documents.select(*(F.col(c).alias(h) for c, h in zip(carried, held, strict=True)), "text")
    fields = ", ".join(f"{h} {source.schema[h].dataType.simpleString()}" for h in held)
    state = "spans_ array<long>, items array<string>"

    def scan(indexes, last: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            shared = [(x, *(np.unpackbits(b).astype(bool) for b in (x.known, x.grams))) for x in indexes.value]
            for batch in batches:
                n_words, n_hit, found, texts, spans = [], [], [], [], []
                column = batch.column("text")
                before = (batch.column("spans_").to_pylist(), batch.column("items").to_pylist()) if "spans_" in batch.schema.names else None
                for c, low in zip(chunks(column), chunks(column, lower=True), strict=True):
                    hit, names = None, [set() for _ in range(low.docs)]
                    for index, known, grams in shared:
                        mask, items = scan_chunk(low, index, known, grams)
                        hit = mask if hit is None else hit | mask
                        for i, which in items.items():
                            names[i] |= {index.ids[k] for k in which} - {None}
                    if before:
                        for i in range(low.docs):
                            runs = before[0][c.first + i]
                            for a, b in zip(runs[0::2], runs[1::2], strict=True):
                                hit[low.at[i] + a : low.at[i] + b] = True
                            names[i] |= set(before[1][c.first + i])
                    found += [sorted(x) for x in names]
                    if not last:
                        spans += spans_of(hit, low.at)
                        continue
                    n_words.append(np.diff(low.at))
                    n_hit.append(low.per_doc(hit, low.at))
                    if clean:
                        c.at, c.starts, c.ends = low.at, low.starts, low.ends
                        texts += [without_hits(c, i, hit) if n else None for i, n in enumerate(n_hit[-1])]
                if not found:
                    continue
                columns, names, listed = [batch.column(h) for h in held], list(held), pa.array(found, pa.list_(pa.string()))
                if not last:
                    yield pa.RecordBatch.from_arrays([*columns, column, pa.array(spans, pa.list_(pa.int64())), listed], [*names, "text", "spans_", "items"])
                    continue
                columns += [*(pa.array(np.concatenate(x).astype(np.int64)) for x in (n_words, n_hit)), listed]
                names += ["n_words", "n_hit", "items"]
                if clean:
                    columns.append(pa.compute.if_else(pa.array(np.concatenate(n_hit) > 0), pa.array(texts, pa.string()), column.cast(pa.string())))
                    names.append("text")
                yield pa.RecordBatch.from_arrays(columns, names)

        return run

    import pyarrow.compute  # noqa: F401

    parts = item_parts(benchmark, 8 * part_words)
    ready = [build_index(p, window) for p in islice(parts, pass_parts)]
    while True:
        more = [build_index(p, window) for p in islice(parts, pass_parts)]
        indexes = spark.sparkContext.broadcast(ready)
        if not more:
            out = source.mapInArrow(scan(indexes, True), f"{fields}, n_words long, n_hit long, items array<string>" + (", text string" if clean else ""))
            return out.select(*(F.col(h).alias(c) for h, c in zip(held, carried, strict=True)), *out.columns[len(held) :])
        source = materialize(source.mapInArrow(scan(indexes, False), f"{fields}, text string, {state}"), "decontam-pass")
        indexes.unpersist()
        ready = more
