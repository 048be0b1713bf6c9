"""Repetition rules: characters inside duplicated word n-grams and duplicated lines.

A text is scanned once in numpy with rolling hashes of several n-gram lengths. Nulls count
as empty texts, which have no words and so fail the base rule; repeated rows are judged one
by one; columns other than the key and the text are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .textkit import SPACE, U, Chunk, chunks, covered, mix, ngram_hash, repeated

SYMBOL = np.zeros(256, bool)
SYMBOL[list(b"#*$%&|<>")] = True


@dataclass(frozen=True)
class RepetitionRules:
    """Largest share of the words' characters inside duplicated n-grams, by n, and inside duplicated lines.

    symbols_per_word is set from labelled documents: of those that pass the base rule no clean one has any symbol.
    """

    ngrams: tuple[tuple[int, float], ...] = ((5, 0.45), (6, 0.44), (7, 0.43), (8, 0.42), (9, 0.41), (10, 0.40))
    line_chars: float = 0.30
    lines: float = 0.50
    symbols_per_word: float = 0.1
    min_words: int = 50
    max_repeat_percent: int = 50


MEASURES = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_lines long, dup_line_chars long"


def measure(chunk: Chunk, lengths: tuple[int, ...]) -> dict[str, np.ndarray]:
    """The counts of each document of a chunk; dup_{n}: characters inside duplicated n-grams."""
    chunk.words()
    data, offsets = chunk.data, chunk.offsets
    head = np.concatenate(([0], np.cumsum((data & 0xC0) != 0x80, dtype=np.int64)))  # code points before each byte
    sizes = head[chunk.ends] - head[chunk.starts]
    doc, hashes = chunk.doc_of_word(), chunk.word_hash()
    out = {"n_words": np.diff(chunk.at), "word_chars": chunk.per_doc(sizes, chunk.at), "n_symbols": chunk.per_doc(SYMBOL[data], offsets)}

    breaks = np.flatnonzero(data == 10)
    starts = np.unique(np.concatenate((offsets[:-1][np.diff(offsets) > 0], (breaks + 1)[breaks + 1 < len(data)])))
    ends = np.concatenate((starts[1:], [len(data)])) if len(starts) else starts
    ends = ends - ((ends > starts) & (data[np.maximum(ends, 1) - 1] == 10)) if len(starts) else ends
    worded = np.searchsorted(chunk.starts, ends) > np.searchsorted(chunk.starts, starts)
    starts, ends = starts[worded], ends[worded]
    line_doc = np.searchsorted(offsets, starts, "right") - 1
    keys = mix(chunk.range_hash(starts, ends) + line_doc.astype(U) * U(0xA24BAED4963EE407))
    _, first = np.unique(keys, return_index=True)
    later = np.ones(len(keys), bool)
    later[first] = False
    out["n_lines"] = np.bincount(line_doc, minlength=chunk.docs)
    out["n_dup_lines"] = np.bincount(line_doc[later], minlength=chunk.docs)
    words_at = np.concatenate(([0], np.cumsum(sizes)))
    line_chars = words_at[np.searchsorted(chunk.starts, ends)] - words_at[np.searchsorted(chunk.starts, starts)]
    out["dup_line_chars"] = np.bincount(line_doc[later], line_chars[later], chunk.docs).astype(np.int64)

    salt, total = doc.astype(U) * U(0x9FB21C651E98DF25), len(hashes)
    alive: np.ndarray | None = None  # starts whose shorter n-gram is repeated: only those can repeat with more words
    for n in sorted({3, *lengths}):
        grams = ngram_hash(hashes, n)
        at = np.flatnonzero(chunk.window_ok(n)) if alive is None else alive[alive <= total - n]
        if alive is not None and len(at):
            at = at[doc[at] == doc[at + n - 1]]
        at = at[repeated(mix(grams[at] + salt[at]))] if len(at) else at
        inside = covered(at, n, total)
        out[f"dup_{n}"] = chunk.per_doc(sizes * inside, chunk.at)
        if n == 3:
            out["n_repeat_words"] = chunk.per_doc(inside, chunk.at)
        alive = at
    return out


def repetition(documents: DataFrame, rules: RepetitionRules = RepetitionRules(), keep: tuple[str, ...] = ()) -> DataFrame:
    """Per row: doc_id, columns of keep, the counts, base_failed, kept and the first rule that it broke.

    A null text has no words. Every row is returned, and repeated rows get the same verdict.
    """
    lengths = tuple(n for n, _ in rules.ngrams)
    extra = [f"dup_{n}" for n in lengths]
    names = [x.split()[0] for x in MEASURES.split(", ")] + [x for x in extra]
    carried = list(dict.fromkeys(("doc_id", *keep)))
    source = documents.select(*dict.fromkeys((*carried, "text")))
    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in source.select(*carried).schema)
    out_schema = f"{fields}, {MEASURES}" + "".join(f", {x} long" for x in extra)

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = [measure(c, lengths) for c in chunks(batch.column("text"))]
            if parts:
                columns = [batch.column(x) for x in carried] + [pa.array(np.concatenate([p[x] for p in parts]).astype(np.int64)) for x in names]
                yield pa.RecordBatch.from_arrays(columns, [*carried, *names])

    counted = source.mapInArrow(scan, out_schema)
    share = lambda part, limit: F.col(part) > F.lit(limit) * F.col("word_chars")
    broken = F.when(F.col("n_words") < rules.min_words, "short").when(100 * F.col("n_repeat_words") > rules.max_repeat_percent * F.col("n_words"), "repeated_words")
    failed = broken.isNotNull()
    verdict = broken
    for n, limit in rules.ngrams:
        verdict = verdict.when(share(f"dup_{n}", limit), f"dup_{n}gram_chars")
    verdict = verdict.when(share("dup_line_chars", rules.line_chars), "dup_line_chars").when(F.col("n_dup_lines") > rules.lines * F.col("n_lines"), "dup_lines")
    verdict = verdict.when(F.col("n_symbols") > rules.symbols_per_word * F.col("n_words"), "symbols")
    return counted.withColumns({"base_failed": failed, "broken_rule": verdict, "kept": verdict.isNull()})
