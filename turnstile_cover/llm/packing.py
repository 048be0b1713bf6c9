"""Cost-balanced packing of tokenised documents into fixed-length training sequences.

Documents are tokenised where they lie and cut at the sequence length; full pieces fill a
sequence alone. The tails go to hashed groups of about ``group_docs`` documents, so a task
holds a bounded number of them. In a group as many sequences are opened as its tokens fill;
tails, longest first, go to the sequence of the lowest cost (linear plus quadratic in the
pieces' lengths) that has room, and a tail that fits nowhere is cut at the roomiest one.
"""

from __future__ import annotations

import base64
import heapq
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from re import compile as regex

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

#: Fixed value: the splitting pattern of the byte-level vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
BLANKS = regex(r"\s |^ | \s| $")
CACHE_ENTRIES = 400_000


@dataclass(frozen=True)
class PackingCost:
    """Cost of a piece of n tokens: linear * n + quadratic * n * n."""

    linear: float = 1.0
    quadratic: float = 1.0 / 4096

    def __call__(self, n):
        return self.linear * n + self.quadratic * n * n


class Encoder:
    """Ids of whole texts, equal to the tokenizer file's, with a cache of blank-separated words.

    A blank between two characters that are not white space always starts a new pre-token, so the
    words of such a text can be encoded one by one. Texts with other blanks are encoded whole, and
    texts that hold the special token's string by the tokenizer file itself.
    """

    def __init__(self, tokenizer_json: str, ranks_file: str):
        import tiktoken

        with open(ranks_file, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.fast = tiktoken.Encoding("ranks", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.path, self.cache = tokenizer_json, {}

    def _special(self, text: str) -> np.ndarray:
        from tokenizers import Tokenizer

        return np.array(Tokenizer.from_file(self.path).encode(text, add_special_tokens=False).ids, "<u2")

    def __call__(self, text: str) -> np.ndarray:
        if "<|" in text and "<|endoftext|>" in text:
            return self._special(text)
        if BLANKS.search(text):
            return np.array(self.fast.encode_ordinary(text), "<u2")
        cache, words = self.cache, text.split(" ")
        if len(cache) > CACHE_ENTRIES:
            cache.clear()
        first = np.array(self.fast.encode_ordinary(words[0]), "<u2").tobytes()
        parts = [cache.get(w) for w in words[1:]]
        if None in parts:
            encode = self.fast.encode_ordinary
            for i, p in enumerate(parts):
                if p is None:
                    w = words[i + 1]
                    p = cache.get(w)
                    if p is None:
                        p = cache[w] = np.array(encode(" " + w), "<u2").tobytes()
                    parts[i] = p
        return np.frombuffer(first + b"".join(parts), "<u2")


@lru_cache(2)
def encoder(tokenizer_json: str, ranks_file: str) -> Encoder:
    return Encoder(tokenizer_json, ranks_file)


def crc(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


def assign(lengths: list[int], size: int, cost: PackingCost) -> list[tuple[int, int, int, int]]:
    """(tail, first token in it, tokens, sequence) of each part, in the order of placement."""
    total = sum(lengths)
    n = -(-total // size)
    room, spent = np.full(n, size, np.int64), np.zeros(n)
    heap = [(-x, i, 0) for i, x in enumerate(lengths)]
    heapq.heapify(heap)
    out = []
    while heap:
        left, i, start = heapq.heappop(heap)
        length = -left
        fits = np.flatnonzero(room >= length)
        if len(fits):
            s = int(fits[np.argmin(spent[fits])])
        else:
            s = int(np.argmax(room))
            heapq.heappush(heap, (int(room[s]) - length, i, start + int(room[s])))
            length = int(room[s])
        out.append((i, start, length, s))
        room[s] -= length
        spent[s] += cost(length)
    return out


def pack(documents: DataFrame, tokenizer_json: str, ranks_file: str, size: int = 2048, end_id: int = 1, group_docs: int = 4096, cost: PackingCost = PackingCost(), with_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids: uint16 bytes).

    A null text is empty: its document is the end token alone. Each row of a repeated document is packed
    for itself. An empty table gives no rows. Sequences are numbered by group and place in it.
    """
    source = documents.select("doc_id", "text")
    key = source.schema["doc_id"].dataType.simpleString()
    groups = max(1, -(-documents.count() // group_docs))
    whole = f"doc_id {key}, row long, start long, ids_crc32 long, doc_tokens long, full boolean, ids binary, grp int"

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, row = encoder(tokenizer_json, ranks_file), 0
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                docs, out = part.column("doc_id").to_pylist(), []
                for doc, text in zip(docs, part.column("text").to_pylist(), strict=True):
                    ids = np.append(encode(text or ""), np.uint16(end_id))
                    row += 1
                    for start in range(0, len(ids), size):
                        piece = ids[start : start + size]
                        full = len(piece) == size
                        group = zlib.crc32(f"{doc}:{row}:{start}".encode()) % groups
                        out.append((doc, row, start, crc(piece) if full else None, len(ids), full, None if full and not with_ids else piece.tobytes(), group))
                columns = [pa.array(x) for x in zip(*out, strict=True)]
                types = [part.schema.field("doc_id").type, pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.binary(), pa.int32()]
                yield pa.RecordBatch.from_arrays([c.cast(t) for c, t in zip(columns, types, strict=True)], ["doc_id", "row", "start", "ids_crc32", "doc_tokens", "full", "ids", "grp"])

    def fill(table: pa.Table) -> pa.Table:
        table = table.sort_by([("full", "ascending"), ("doc_id", "ascending"), ("start", "ascending"), ("row", "ascending")])
        rows = {n: table.column(n).to_pylist() for n in ("start", "ids_crc32", "full", "ids")}
        tails = [i for i, full in enumerate(rows["full"]) if not full]
        ids = [np.frombuffer(rows["ids"][i], "<u2") for i in tails]
        base, used = table.column("grp")[0].as_py() << 32, {}
        out: list[tuple[int, int, int, int, int, int, bytes | None]] = []
        for t, start, length, s in assign([len(x) for x in ids], size, cost):
            piece = ids[t][start : start + length]
            out.append((tails[t], rows["start"][tails[t]] + start, length, crc(piece), base + s, used.get(s, 0), piece.tobytes() if with_ids else None))
            used[s] = used.get(s, 0) + length
        for k, i in enumerate(i for i, full in enumerate(rows["full"]) if full):
            out.append((i, rows["start"][i], size, rows["ids_crc32"][i], base + len(used) + k, 0, rows["ids"][i]))
        take, *columns = zip(*out, strict=True)
        picked = table.select(["doc_id", "doc_tokens"]).take(pa.array(take))
        result = {"doc_id": picked.column("doc_id")}
        for name, c in zip(("start", "length", "ids_crc32"), columns, strict=False):
            result[name] = pa.array(c, pa.int64())
        result["doc_tokens"] = picked.column("doc_tokens")
        result["sequence_id"], result["offset"] = pa.array(columns[3], pa.int64()), pa.array(columns[4], pa.int64())
        if with_ids:
            result["ids"] = pa.array(columns[5], pa.binary())
        return pa.table(result)

    schema = f"doc_id {key}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + (", ids binary" if with_ids else "")
    return source.mapInArrow(cut, whole).groupBy("grp").applyInArrow(fill, schema)


def padding(pieces: DataFrame, size: int = 2048) -> DataFrame:
    """One row: sequences, tokens, padded tokens and the share of padding; a power of two needs none."""
    sequences = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    exact = F.bit_count("n") == 1
    total = sequences.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), F.sum(F.when(exact, 0).otherwise(size - F.col("n"))).alias("padded"))
    return total.withColumn("share", F.try_divide("padded", F.col("tokens") + F.col("padded")))
