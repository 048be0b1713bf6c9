"""Language identification: multinomial logistic regression on TF-IDF character n-grams.

n-grams of characters are hashed from the text's bytes without decoding it. Document
frequencies cover every training row; the sparse weights are fitted by follow-the-regularised-
leader with an elastic-net penalty on a bounded sample, and one temperature is calibrated on
rows that the fit did not see.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from .textkit import U, Chunk, chunks

BITS = 16
ORDERS = (1, 2, 3)
SCALE = 30.0
LETTER = np.zeros(256, bool)
LETTER[[*range(65, 91), *range(97, 123)]] = True


def gram_buckets(c: Chunk) -> list[tuple[np.ndarray, np.ndarray]]:
    """For each order: the bucket of every n-gram inside a document, and where each document's begin."""
    head = np.flatnonzero((c.data & 0xC0) != 0x80)
    ends = np.append(head, len(c.data))
    first = np.searchsorted(head, c.offsets)
    out = []
    for n in ORDERS:
        if len(head) < n:
            out.append((np.empty(0, np.int64), np.zeros(c.docs + 1, np.int64)))
            continue
        b = c.range_hash(head[: len(head) - n + 1], ends[n:]) >> U(64 - BITS)
        inside = np.ones(len(b), bool)
        for end in np.unique(first[1:-1]):
            inside[max(0, end - n + 1) : end] = False
        at = np.concatenate(([0], np.cumsum(inside)))[np.minimum(first, len(b))]
        out.append((b[inside].astype(np.int64), at))
    return out


def document_buckets(c: Chunk) -> Iterator[np.ndarray]:
    parts = gram_buckets(c)
    for i in range(c.docs):
        yield np.concatenate([b[at[i] : at[i + 1]] for b, at in parts])


def has_letter(c: Chunk) -> np.ndarray:
    """Does each document hold a letter? Only texts without an ASCII letter are decoded."""
    some = c.per_doc(LETTER[c.data], c.offsets) > 0
    for i in np.flatnonzero(~some & (np.diff(c.offsets) > 0)):
        some[i] = any(x.isalpha() for x in c.data[c.offsets[i] : c.offsets[i + 1]].tobytes().decode())
    return some


@dataclass
class LanguageModel:
    """table: weight of each bucket and language, already times its inverse document frequency."""

    languages: list[str]
    table: np.ndarray
    bias: np.ndarray
    temperature: float

    def logits(self, c: Chunk) -> np.ndarray:
        total, n = np.zeros((c.docs, len(self.languages))), np.zeros(c.docs)
        for b, at in gram_buckets(c):
            n += np.diff(at)
            some = np.flatnonzero(np.diff(at))
            if len(some):
                total[some] += np.add.reduceat(self.table[b], at[some], axis=0)
        return total * (SCALE / np.maximum(n, 1))[:, None] + self.bias

    def predict(self, c: Chunk) -> tuple[np.ndarray, np.ndarray]:
        p = softmax(self.logits(c) / self.temperature)
        best = p.argmax(1)
        return best, p[np.arange(c.docs), best]


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


@dataclass(frozen=True)
class Ftrl:
    """Follow-the-regularised-leader with per-coordinate rates and elastic-net penalties."""

    alpha: float = 0.5
    beta: float = 1.0
    l1: float = 0.002
    l2: float = 0.01
    epochs: int = 4

    def weights(self, z: np.ndarray, n: np.ndarray) -> np.ndarray:
        small = np.abs(z) <= self.l1
        return np.where(small, 0.0, (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def fit(self, rows: list[tuple[np.ndarray, np.ndarray]], labels: list[int], classes: int) -> tuple[np.ndarray, np.ndarray]:
        """Weights and bias from sparse rows (buckets, values)."""
        size = (1 << BITS) + 1  # the last one is the bias
        z, n = np.zeros((size, classes)), np.zeros((size, classes))
        for epoch in range(self.epochs):
            for i in np.random.default_rng(epoch).permutation(len(rows)):
                at, x = np.append(rows[i][0], size - 1), np.append(rows[i][1], 1.0)[:, None]
                w = self.weights(z[at], n[at])
                g = softmax((x * w).sum(0))
                g[labels[i]] -= 1
                g = x * g
                sigma = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / self.alpha
                z[at] += g - sigma * w
                n[at] += g * g
        w = self.weights(z, n)
        return w[:-1], w[-1]


def calibrate(logits: np.ndarray, labels: np.ndarray) -> float:
    """The temperature that maximises the likelihood of held-back rows, by golden section on its logarithm."""
    if not len(labels):
        return 1.0

    def loss(t: float) -> float:
        z = logits / np.exp(t)
        return float((np.logaddexp.reduce(z, axis=1) - z[np.arange(len(labels)), labels]).mean())

    lo, hi, g = -4.0, 4.0, (5**0.5 - 1) / 2
    for _ in range(40):
        a, b = hi - g * (hi - lo), lo + g * (hi - lo)
        lo, hi = (lo, b) if loss(a) <= loss(b) else (a, hi)
    return float(np.exp((lo + hi) / 2))


def document_frequencies(training: DataFrame) -> tuple[int, np.ndarray]:
    """Documents, and documents with each bucket, over all rows of training."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        df, docs = np.zeros((1 << BITS) + 1, np.int64), 0
        for batch in batches:
            for c in chunks(batch.column("text"), lower=True):
                for b in document_buckets(c):
                    docs += 1
                    if len(b) > 4096:
                        df[:-1] += np.bincount(b, minlength=1 << BITS) > 0
                    else:
                        df[np.unique(b)] += 1
        df[-1] = docs
        at = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(df[at], pa.int64())], ["bucket", "df"])

    rows = training.select("text").mapInArrow(count, "bucket long, df long").groupBy("bucket").agg(F.sum("df").alias("df")).collect()  # at most one row a bucket
    out = np.zeros((1 << BITS) + 1, np.int64)
    for b, n in rows:
        out[b] = n
    return int(out[-1]), out[:-1]


def fit(training: DataFrame, max_rows: int = 4000, max_chars: int = 20_000, min_rows: int = 20, ftrl: Ftrl = Ftrl()) -> LanguageModel | None:
    """A model of training's text and lang (nulls left out); None if there is nothing to learn.

    The fit sees at most max_rows different texts (copies count once), spread evenly over the languages in hashed order, of
    at most max_chars characters; a language with fewer than min_rows such texts adds up to so many longer ones, whole.
    Document frequencies cover all rows.
    """
    rows = training.select("text", "lang").where(F.col("text").isNotNull() & F.col("lang").isNotNull())
    docs, df = document_frequencies(rows)
    h, long = F.xxhash64("text"), F.length("text") > max_chars
    texts = rows.select("lang", "text", h.alias("h"), long.alias("long"), (F.pmod(h, F.lit(1 << 30)) / (1 << 30)).alias("at"))
    counts = {(r[0], r[1]): r[2] for r in texts.groupBy("lang", "long").agg(F.approx_count_distinct("h")).collect()}  # two rows a language
    if not counts:
        return None
    languages = sorted({k for k, _ in counts})
    quota = {(k, False): max(min_rows, max_rows // len(languages)) for k in languages}
    quota |= {(k, True): min_rows for k in languages if counts.get((k, False), 0) < min_rows}
    groups = [x for x in sorted(quota) if x in counts]
    of = lambda value: F.create_map(*[F.lit(x) for k, y in groups for x in (f"{k}/{y}", value((k, y)))])[F.concat("lang", F.lit("/"), F.when(F.col("long"), "True").otherwise("False"))]
    near = texts.where(F.col("at") <= of(lambda g: min(1.0, 1.3 * (quota[g] + 10) / counts[g])))
    different = near.groupBy("lang", "long", "at", "h").agg(F.min("text").alias("text"))  # copies collapse before anything is sent
    place = F.row_number().over(Window.partitionBy("lang", "long").orderBy("at", "h"))  # a little over the quota in each group
    picked = different.withColumn("place", place).where(F.col("place") <= of(lambda g: quota[g])).select("lang", "text", F.col("place").alias("order"))

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at, value = [], []
            for c in chunks(batch.column("text"), lower=True):
                for b in document_buckets(c):
                    u, n = np.unique(b, return_counts=True)
                    at.append(u.astype("<u2").tobytes())
                    value.append((n / max(1, len(b))).astype("<f4").tobytes())
            if at:
                yield pa.RecordBatch.from_arrays([batch.column("lang"), batch.column("order"), pa.array(at, pa.binary()), pa.array(value, pa.binary())], ["lang", "ordered", "at", "value"])

    sample: dict[str, list] = {k: [] for k in languages}
    for r in sorted(picked.mapInArrow(features, "lang string, ordered int, at binary, value binary").collect()):  # at most the quotas
        sample[r[0]].append(r)
    idf = np.log((1 + docs) / (1 + df))
    data, labels, back, back_labels = [], [], [], []
    for y, k in enumerate(languages):
        for i, r in enumerate(sample[k]):
            u = np.frombuffer(r[2], "<u2").astype(np.int64)
            x = (u, SCALE * np.frombuffer(r[3], "<f4") * idf[u])
            (back if i % 5 == 4 else data).append(x)
            (back_labels if i % 5 == 4 else labels).append(y)
    w, bias = ftrl.fit(data, labels, len(languages))
    logits = np.array([(x[1][:, None] * w[x[0]]).sum(0) + bias for x in back]).reshape(-1, len(languages))
    return LanguageModel(languages, (w * idf[:, None]).astype(np.float32), bias, calibrate(logits, np.array(back_labels, int)))


def identify(documents: DataFrame, model: LanguageModel | None, keep: tuple[str, ...] = ()) -> DataFrame:
    """Per row: doc_id, columns of keep, lang_pred and score.

    A null text, one without a letter, or any text where nothing was learned is `und` with score 0; repeated rows get the
    same answer, ties go to the first language by name, and texts of any length are read whole.
    """
    shared = documents.sparkSession.sparkContext.broadcast(model)
    carried = list(dict.fromkeys(("doc_id", *keep)))
    source = documents.select(*dict.fromkeys((*carried, "text")))
    fields = ", ".join(f"`{x.name}` {x.dataType.simpleString()}" for x in source.select(*carried).schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        names = np.array([*(m.languages if m else []), "und"], object)
        for batch in batches:
            langs, scores = [], []
            for c, low in zip(chunks(batch.column("text")), chunks(batch.column("text"), lower=True), strict=True):
                known = has_letter(c) if m else np.zeros(c.docs, bool)
                best, score = m.predict(low) if m else (np.zeros(c.docs, int), np.zeros(c.docs))
                langs.append(names[np.where(known, best, len(names) - 1)])
                scores.append(np.where(known, score, 0.0))
            if langs:
                yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in carried), pa.array(np.concatenate(langs), pa.string()), pa.array(np.concatenate(scores))], [*carried, "lang_pred", "score"])

    return source.mapInArrow(run, f"{fields}, lang_pred string, score double")


def fold(doc_id: str, n: int) -> Column:
    """crc32 of the id as text, modulo n."""
    return F.crc32(F.col(doc_id).cast("string")) % n
