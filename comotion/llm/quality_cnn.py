"""Quality classifier (operator 6): a byte-level convolutional network in numpy.

A document is its UTF-8 bytes, cut into overlapping chunks that cover it whole. Learned filters, ``TAPS`` byte pairs wide
and moving by one pair, run over each chunk; each filter's response is rectified and max-pooled over the chunk; the pooled
vectors are averaged and maximised over the chunks, and a logistic unit turns both into one probability. A filter holds one
learned value for every byte at every place, so a response is a sum of table entries.

Training reads at most ``PER_LABEL`` labelled rows of each label (smallest hashes of doc_id), never held-out ones, whole
texts, and of these in the order of their hashes what fits into ``SAMPLE_BYTES`` bytes. Defined results: null and empty texts are one chunk of padding and get a score too; equal texts get equal scores;
without labels every score is 0.5; very long texts are scored whole, slice by slice.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.llm.common import doc_text, hash_sample, held_out, record, slices, small_table

PER_LABEL = 800
SAMPLE_BYTES = 64 << 20
FILTERS = 12
TAPS = 3  # byte pairs, so 6 bytes
CHUNK, OVERLAP = 512, 32  # bytes
THRESHOLD = 0.3
SCHEMA = "doc_id long, score double, predicted int"
_BLOCK = 2048  # chunks at a time


def chunks(raw: bytes) -> np.ndarray:
    """Rows of ``CHUNK`` bytes; the last one is padded with zero bytes."""
    step = CHUNK - OVERLAP
    n = max(1, -(-max(0, len(raw) - OVERLAP) // step))
    data = np.frombuffer(raw.ljust((n - 1) * step + CHUNK, b"\0"), np.uint8)
    return np.lib.stride_tricks.sliding_window_view(data, CHUNK)[::step]


@dataclass
class Network:
    kernel: np.ndarray  # 2*TAPS x 256 x FILTERS
    bias: np.ndarray
    out: np.ndarray  # 2*FILTERS
    out_bias: float

    def __post_init__(self):
        self._pairs = None

    def pair_tables(self) -> np.ndarray:
        """TAPS x 65536 x FILTERS: both bytes of a little-endian pair at once."""
        if self._pairs is None:
            low, high = self.kernel[0::2], self.kernel[1::2]
            self._pairs = (high[:, :, None, :] + low[:, None, :, :]).reshape(TAPS, 65536, FILTERS).astype(np.float32)
        return self._pairs

    def pooled(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Maximum of each filter over each chunk, and where it is."""
        pairs = np.ascontiguousarray(rows).view("<u2")
        tables, n = self.pair_tables(), pairs.shape[1] - TAPS + 1
        reply = tables[0][pairs[:, :n]]
        for k in range(1, TAPS):
            reply += tables[k][pairs[:, k : k + n]]
        spot = reply.argmax(1)
        return np.maximum(np.take_along_axis(reply, spot[:, None, :], 1)[:, 0] + self.bias, 0), spot

    def peaks(self, rows: np.ndarray) -> np.ndarray:
        pairs = np.ascontiguousarray(rows).view("<u2")
        tables, n = self.pair_tables(), pairs.shape[1] - TAPS + 1
        best = np.empty((len(pairs), FILTERS), np.float32)
        for a in range(0, len(pairs), 16):
            p = pairs[a : a + 16]
            reply = tables[0].take(p[:, :n], axis=0)
            for k in range(1, TAPS):
                reply += tables[k].take(p[:, k : k + n], axis=0)
            reply.max(1, out=best[a : a + 16])
        return np.maximum(best + self.bias, 0)

    def probability(self, raw: bytes) -> float:
        rows, total, most = chunks(raw), 0.0, np.zeros(FILTERS)
        for a in range(0, len(rows), _BLOCK):
            p = self.peaks(rows[a : a + _BLOCK])
            total, most = total + p.sum(0, dtype=np.float64), np.maximum(most, p.max(0))
        z = np.concatenate((total / len(rows), most)) @ self.out + self.out_bias
        return float(1 / (1 + np.exp(-z)))


def fit(texts: list[bytes], labels: list[int], epochs: int = 6, seed: int = 3) -> Network:
    rng = np.random.default_rng(seed)
    net = Network(rng.normal(0, 0.15, (2 * TAPS, 256, FILTERS)), np.zeros(FILTERS), rng.normal(0, 0.3, 2 * FILTERS), 0.0)
    if len(set(labels)) < 2:
        net.out, net.out_bias = np.zeros(2 * FILTERS), 0.0
        return net
    y, share = np.array(labels, float), np.bincount(labels, minlength=2) / len(labels)
    params = [net.kernel, net.bias, net.out, np.zeros(1)]
    first, second = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
    step = 0
    for _ in range(epochs):
        order = rng.permutation(len(texts))
        for lo in range(0, len(order), 16):
            own = order[lo : lo + 16]
            parts = [chunks(texts[i]) for i in own]
            rows = np.concatenate(parts)
            owner = np.repeat(np.arange(len(own)), [len(p) for p in parts])
            count = np.bincount(owner, minlength=len(own))
            spots, tops = [], []
            net._pairs = None
            for a in range(0, len(rows), 128):
                top, spot = net.pooled(rows[a : a + 128])
                tops.append(top)
                spots.append(spot)
            top, spot = np.concatenate(tops), np.concatenate(spots)
            mean = np.stack([np.bincount(owner, top[:, f], len(own)) for f in range(FILTERS)], 1) / count[:, None]
            starts = np.concatenate(([0], np.cumsum(count)[:-1]))
            most = np.maximum.reduceat(top, starts, axis=0)
            x = np.concatenate((mean, most), 1)
            p = 1 / (1 + np.exp(-np.clip(x @ net.out + params[3][0], -30, 30)))
            g = (p - y[own]) / (2 * share[y[own].astype(int)]) / len(own)
            gx = g[:, None] * net.out
            gtop = gx[owner, :FILTERS] / count[owner, None]
            lead = top >= most[owner]
            ties = np.stack([np.bincount(owner, lead[:, f], len(own)) for f in range(FILTERS)], 1)
            gtop = (gtop + lead * gx[owner, FILTERS:] / np.maximum(ties, 1)[owner]) * (top > 0)
            gk = np.zeros_like(net.kernel)
            filters = np.broadcast_to(np.arange(FILTERS), spot.shape)
            for k in range(2 * TAPS):
                byte = np.take_along_axis(rows, 2 * spot + k, 1)
                np.add.at(gk[k], (byte, filters), gtop)
            grads = [gk, gtop.sum(0), x.T @ g + 1e-4 * net.out, np.array([g.sum()])]
            step += 1
            for i, gr in enumerate(grads):
                first[i] = 0.9 * first[i] + 0.1 * gr
                second[i] = 0.99 * second[i] + 0.01 * gr * gr
                params[i] -= 0.02 * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.99**step)) + 1e-7)
    net.out_bias = float(params[3][0])
    # training weighs both labels alike; the prior of the sample's rows belongs to the caller
    net._pairs = None
    return net


def train(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL) -> Network:
    lab = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality"))
    lab = lab.filter(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    spark, text = docs.sparkSession, F.coalesce("text", F.lit(""))
    picked = {(r.doc_id, r.quality) for r in hash_sample(lab, "quality", per_label, 2).collect()}
    if not picked:
        return fit([], [])
    sample = F.broadcast(small_table(spark, sorted(picked), "doc_id long, _quality int"))
    sizes = doc_text(docs).join(sample, "doc_id").select("doc_id", F.octet_length(text).alias("n")).groupBy("doc_id").agg(F.sum("n").alias("n"), F.min(F.xxhash64("doc_id")).alias("h")).collect()
    fits, room = set(), SAMPLE_BYTES
    for r in sorted(sizes, key=lambda r: (r.h, r.doc_id)):
        if r.n <= room:
            fits.add(r.doc_id)
            room -= r.n
    sample = F.broadcast(small_table(spark, sorted(x for x in picked if x[0] in fits), "doc_id long, _quality int"))
    rows = doc_text(docs).join(sample, "doc_id").select(text.cast("binary").alias("raw"), "_quality").collect()
    rows.sort(key=lambda r: (r._quality, bytes(r.raw)))
    return fit([bytes(r.raw) for r in rows], [r._quality for r in rows])


def score(docs: DataFrame, net: Network) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(net)
    out = pa.schema([("doc_id", pa.int64()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            p = [shared.value.probability((t or "").encode()) for t in b.column(1).to_pylist()]
            yield record(out, b.column(0), p, [int(x >= THRESHOLD) for x in p])

    return doc_text(docs).mapInArrow(run, SCHEMA)
