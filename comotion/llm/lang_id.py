"""Language identification (operator 1) with error-correcting output codes.

Each language owns a codeword of bits. For each bit a binary classifier over hashed byte n-grams (lengths 1 to 3, relative
frequencies of the lower-cased text) predicts that bit. Decoding weighs every classifier's logistic loss by its accuracy in
training and picks the nearest codeword; the loss gap to the runner-up flags ambiguity.

Training reads a bounded sample: at most ``PER_LANGUAGE`` rows of each language (smallest hashes of doc_id) and
``SAMPLE_ROWS`` in all, never held-out ones; the code covers the ``MAX_LANGUAGES`` most frequent languages. Prediction reads
whole texts and nothing else.

Defined results: null text, or text without a letter, is ``und`` with score 0; without any labelled row every text is
``und``; equal texts get equal results; very long texts are counted whole, slice by slice.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.llm.common import doc_text, hash_sample, held_out, record, slices, small_table

DIM_BITS = 12
PER_LANGUAGE = 400
MAX_LANGUAGES = 256
SAMPLE_ROWS = 16_384  # 16 kB each on the driver
#: Softmax gap between best and second codeword under which a text is ambiguous.
AMBIGUOUS = 0.2
SCHEMA = "doc_id long, lang_pred string, score double, runner_up string, ambiguous boolean, bit_errors int"
LETTER = regex.compile(r"\p{L}")
_CHUNK = 1 << 20
_MULT = (np.uint32(0x9E3779B1), np.uint32(0x85EBCA6B), np.uint32(0xC2B2AE35))


def gram_codes(data: np.ndarray) -> list[np.ndarray]:
    """Bucket of the 1-, 2- and 3-gram that ends at each byte (the first ones shorter lists)."""
    shift = np.uint32(32 - DIM_BITS)
    b = data.astype(np.uint32) + np.uint32(1)
    one = b * _MULT[0]
    two = (b[:-1] * np.uint32(257) + b[1:]) * _MULT[1]
    three = ((b[:-2] * np.uint32(257) + b[1:-1]) * np.uint32(257) + b[2:]) * _MULT[2]
    return [x >> shift for x in (one, two, three)]


def features(text: str) -> np.ndarray:
    """Relative frequencies of the hashed n-grams, each length counting a third."""
    data = np.frombuffer(text.lower().encode(), np.uint8)
    out = np.zeros(1 << DIM_BITS)
    for lo in range(0, max(1, len(data)), _CHUNK):
        for k, codes in enumerate(gram_codes(data[max(0, lo - 2) : lo + _CHUNK])):
            codes = codes[min(lo, 2 - k) :]  # those that end before the chunk are counted already
            out += np.bincount(codes, minlength=1 << DIM_BITS)
    return (out / max(1.0, out.sum())).astype(np.float32)


def code_book(n: int, seed: int = 7) -> np.ndarray:
    """n codewords of -1 and 1. Few classes get every useful column; more get random columns with the widest least distance."""
    if n <= 2:
        return np.array([[-1.0], [1.0]][:n])
    if n <= 7:
        cols = np.arange(1, 1 << (n - 1))
        bits = np.concatenate([np.ones((1, len(cols)), int), (cols >> np.arange(n - 1)[:, None] & 1) ^ 1])
        return np.where(bits, 1.0, -1.0)
    rng, length = np.random.default_rng(seed), int(np.ceil(10 * np.log2(n)))
    tries = [rng.choice([-1.0, 1.0], (n, length)) for _ in range(50)]
    return max(tries, key=lambda m: (length - np.abs(m @ m.T - 2 * length * np.eye(n)).max()))


@dataclass
class Model:
    languages: list[str]
    book: np.ndarray
    weights: np.ndarray  # bits x buckets
    bias: np.ndarray
    trust: np.ndarray  # bits

    @property
    def correctable(self) -> int:
        """Wrong bits that the code can always put right."""
        n, length = self.book.shape
        if n < 2:
            return 0
        least = min((length - self.book[i] @ self.book[j]) / 2 for i in range(n) for j in range(i))
        return int((least - 1) // 2)

    def decode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Best and second language, their softmax scores, and wrong bits against the best codeword."""
        margins = x @ self.weights.T + self.bias
        loss = (np.logaddexp(0, -margins[:, None, :] * self.book[None]) * self.trust).sum(2) / self.trust.sum()
        p = np.exp(-(loss - loss.min(1, keepdims=True)) * 4)
        p /= p.sum(1, keepdims=True)
        order = np.argsort(-p, axis=1, kind="stable")
        errors = (np.sign(margins) != self.book[order[:, 0]]).sum(1)
        return order, p, np.take_along_axis(p, order, 1), errors


def fit(texts: list[np.ndarray], langs: list[str], rounds: int = 300) -> Model | None:
    """Logistic regressions for all bits at once, by accelerated full-batch gradient steps."""
    names = sorted(set(langs))
    if not names:
        return None
    number = {v: k for k, v in enumerate(names)}
    x = np.stack(texts).astype(np.float32)
    y = np.array([number[v] for v in langs])
    book = code_book(len(names))
    scale = (1 / (x.std(0) + 1e-4)).astype(np.float32)
    mean = x.mean(0)
    z = (x - mean) * scale
    target = book[y].astype(np.float32)
    share = np.bincount(y, minlength=len(names))[y]
    weight = (1 / share / len(names))[:, None].astype(np.float32)
    w, v = np.zeros((z.shape[1], book.shape[1]), np.float32), 0.0
    bias, vb = np.zeros(book.shape[1], np.float32), 0.0
    rate, decay = np.float32(8.0 / float((z * z).sum(1).mean())), np.float32(1e-3)
    for _ in range(rounds):
        m = z @ w + bias
        g = -target / (1 + np.exp(np.clip(m * target, -30, 30))) * weight
        v, vb = 0.9 * v - rate * (z.T @ g + decay * w), 0.9 * vb - rate * g.sum(0)
        w, bias = w + v, bias + vb
    right = ((np.sign(z @ w + bias) == target) * weight).sum(0)
    trust = np.clip(2 * right - 1, 0.05, 1.0)
    real = w * scale[:, None]
    return Model(names, book, real.T.astype(np.float32), (bias - mean @ real).astype(np.float32), trust)


def train(docs: DataFrame, per_language: int = PER_LANGUAGE) -> Model | None:
    """Learns from rows that are not held out and have a language; text and lang only."""
    known = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").isNotNull().alias("has"))
    known = known.filter(F.col("has") & F.col("doc_id").isNotNull() & F.col("lang").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", "lang")
    n = max(1, min(MAX_LANGUAGES, known.select("lang").distinct().limit(MAX_LANGUAGES).count()))
    ids = hash_sample(known, "lang", min(per_language, SAMPLE_ROWS // n), MAX_LANGUAGES)
    out = pa.schema([("lang", pa.string()), ("x", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            yield record(out, b.column(2), [features(t).tobytes() for t in b.column(1).to_pylist()])

    picked = [(r.doc_id, r.lang) for r in ids.collect()]
    if not picked:
        return None
    sample = small_table(docs.sparkSession, sorted(set(picked)), "doc_id long, _lang string")  # ``SAMPLE_ROWS`` at most
    rows = doc_text(docs).filter(F.col("text").isNotNull()).join(F.broadcast(sample), "doc_id").select("doc_id", "text", "_lang").mapInArrow(run, "lang string, x binary").collect()
    rows.sort(key=lambda r: (r.lang, bytes(r.x)))
    return fit([np.frombuffer(r.x, np.float32) for r in rows], [r.lang for r in rows])


def block_features(texts: list[str]) -> np.ndarray:
    return np.stack([features(t) for t in texts])


def classify(texts: list[str | None], model: Model | None) -> list[tuple]:
    """(language, score, runner-up, ambiguous, wrong bits) of each text."""
    out: list[tuple] = [("und", 0.0, None, True, 0)] * len(texts)
    spots = [i for i, t in enumerate(texts) if t and model is not None and LETTER.search(t)]
    for k in range(0, len(spots), 256):
        own = spots[k : k + 256]
        order, _, p, errors = model.decode(block_features([texts[i] for i in own]))
        for r, i in enumerate(own):
            second = model.languages[order[r, 1]] if len(model.languages) > 1 else None
            gap = p[r, 0] - p[r, 1] if second else 1.0
            out[i] = (model.languages[order[r, 0]], float(p[r, 0]), second, bool(gap < AMBIGUOUS), int(errors[r]))
    return out


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kinds = (pa.int64(), pa.string(), pa.float64(), pa.string(), pa.bool_(), pa.int32())
    out = pa.schema(list(zip([c.split()[0] for c in SCHEMA.split(", ")], kinds)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            yield record(out, b.column(0), *zip(*classify(b.column(1).to_pylist(), shared.value)))

    return doc_text(docs).mapInArrow(run, SCHEMA)


def rejected(lang_pred: str, ambiguous: bool, bit_errors: int, model: Model | None) -> bool:
    """No language at all, or an ambiguous text with more wrong bits than the code can put right."""
    return lang_pred == "und" or (ambiguous and model is not None and bit_errors > model.correctable + 1)


def keep_identified(docs: DataFrame, model: Model | None) -> DataFrame:
    """The rows of ``docs``, all columns, whose language is identified; only texts go to Python, and only flags come back."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def identified(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for column in texts:
            flags: list[bool] = []
            for b in slices(iter([pa.RecordBatch.from_arrays([column], names=["text"])]), 1 << 20):
                flags += [not rejected(g[0], g[3], g[4], shared.value) for g in classify(b.column(0).to_pylist(), shared.value)]
            yield pa.array(flags, pa.bool_())

    return docs.filter(F.arrow_udf(identified, "boolean")(F.col("text").cast("string")))
