"""Toxicity (operator 4): cumulative-link ordinal regression over sparse word features.

P(grade > j) = sigmoid(w·x - c_j): one weight vector, ordered cut points c_0 < c_1 < ... The features of a text are its
vocabulary words, one each, whatever their count; the vocabulary comes from the training sample and is bounded.
The result holds the expected severity, that is the sum of P(grade > j).

Grades: ``labels.toxic`` = 0 is grade 0. A toxic text has grade 1, 2 or 3 when it holds at most one, two or three, or more
distinct words that occur far more often in the toxic sample than in the clean one.

Training reads at most ``PER_LABEL`` rows of each label (smallest hashes of doc_id), never held-out ones. Defined results:
null and empty texts score as a text without words; without labels every severity is 0; equal texts get equal results.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from comotion.llm.common import doc_text, hash_sample, held_out, record, slices, small_table

PER_LABEL = 1500
VOCABULARY = 20_000
LEAST_TEXTS = 6
#: Soft threshold of the weights at each step: most words end with no weight.
SPARSITY = 0.001
GRADES = 4
#: Expected severity from which a text is flagged.
FLAG = 0.4
SCHEMA = "doc_id long, severity double, grade int, toxic_probability double, flagged boolean"
WORD = regex.compile(r"\p{L}+")


def words(text: str | None) -> set[str]:
    return set(WORD.findall(text.lower())) if text else set()


@dataclass
class Model:
    weights: dict[str, float]
    cuts: np.ndarray

    def exceed(self, own: set[str]) -> np.ndarray:
        """P(grade > j) for each threshold j."""
        known = own & self.weights.keys() if len(own) > len(self.weights) else (w for w in own if w in self.weights)
        return 1 / (1 + np.exp(self.cuts - sum(map(self.weights.__getitem__, known))))


def telling_words(texts: list[set[str]], toxic: list[int], least: int = 5, ratio: float = 12.0) -> set[str]:
    """Words whose share of toxic texts is at least ``ratio`` times that of clean ones."""
    bad, good = Counter(), Counter()
    for own, t in zip(texts, toxic):
        (bad if t else good).update(own)
    n_bad, n_good = max(1, sum(toxic)), max(1, len(toxic) - sum(toxic))
    return {w for w, n in bad.items() if n >= least and n / n_bad >= ratio * (good[w] + 0.5) / n_good}


def screened(texts: list[set[str]], toxic: list[int], least: float = 15.0) -> list[str]:
    """Words whose presence and the label depend on each other, by the chi-square statistic; at most ``VOCABULARY``."""
    df, bad = Counter(w for t in texts for w in t), Counter(w for t, y in zip(texts, toxic) if y for w in t)
    n, n_bad = len(texts), sum(toxic)

    def chi(w: str) -> float:
        a, b = bad[w], df[w]
        spread = n_bad * (n - n_bad) * b * (n - b)
        return n * (a * n - b * n_bad) ** 2 / spread if spread else 0.0

    scores = {w: s for w, k in df.items() if k >= LEAST_TEXTS and (s := chi(w)) >= least}
    return sorted(scores, key=lambda w: (-scores[w], w))[:VOCABULARY]


def grade_of(own: set[str], toxic: int, telling: set[str]) -> int:
    n = len(own & telling)
    return 0 if not toxic else 1 if n <= 1 else 2 if n <= 3 else 3


def cuts_of(gap: np.ndarray) -> np.ndarray:
    """Ordered cut points from the first one and the logarithms of the steps."""
    return gap[0] + np.concatenate(([0.0], np.cumsum(np.exp(gap[1:]))))


def loss(w: np.ndarray, gap: np.ndarray, rows: np.ndarray, cols: np.ndarray, above: np.ndarray, balance: np.ndarray) -> tuple[float, np.ndarray, np.ndarray]:
    """Weighted logistic loss of all thresholds, and its gradients by weights and cut parameters. Text rows[i] holds word cols[i]."""
    reach = np.clip(cuts_of(gap) - np.bincount(rows, weights=w[cols], minlength=len(above))[:, None], -30, 30)
    value = float(((np.logaddexp(0, reach) - (1 - above) * reach) * balance[:, None]).sum())
    diff = (1 / (1 + np.exp(reach)) - above) * balance[:, None]
    by_cut = -diff.sum(0)
    steps = [by_cut[k + 1 :].sum() * np.exp(gap[k + 1]) for k in range(len(gap) - 1)]
    return value, np.bincount(cols, weights=diff.sum(1)[rows], minlength=len(w)), np.array([by_cut.sum(), *steps])


def fit(texts: list[set[str]], toxic: list[int], rounds: int = 400) -> Model:
    if not texts or not any(toxic):
        return Model({}, np.full(GRADES - 1, 20.0))
    telling = telling_words(texts, toxic)
    grade = np.array([grade_of(t, y, telling) for t, y in zip(texts, toxic)])
    vocabulary = screened(texts, toxic)
    at = {w: i for i, w in enumerate(vocabulary)}
    rows = np.concatenate([np.full(len(own), i) for i, t in enumerate(texts) if (own := [w for w in t if w in at]) or True] or [[]]).astype(int)
    cols = np.array([at[w] for t in texts for w in [x for x in t if x in at]], int)
    n, d = len(texts), len(at)
    balance = np.where(grade > 0, 0.5 / max(1, (grade > 0).sum()), 0.5 / max(1, (grade == 0).sum()))
    above = (grade[:, None] > np.arange(GRADES - 1)).astype(float)
    w, gap = np.zeros(d), np.zeros(GRADES - 1)  # gap: the first cut, then log steps, which keep the cuts ordered
    ahead, ahead_gap = w, gap
    rate = 1 / (0.75 * max(1, np.bincount(rows, minlength=1).max()))
    for step in range(1, rounds + 1):  # accelerated proximal gradient
        _, g, gg = loss(ahead, ahead_gap, rows, cols, above, balance)
        moved = ahead - rate * g
        new = np.sign(moved) * np.maximum(np.abs(moved) - rate * SPARSITY, 0)
        new_gap = ahead_gap - 0.2 * gg
        speed = (step - 1) / (step + 2)
        ahead, ahead_gap = new + speed * (new - w), new_gap + speed * (new_gap - gap)
        w, gap = new, new_gap
    cuts = cuts_of(gap)
    return Model({word: float(w[i]) for word, i in at.items() if abs(w[i]) > 1e-3}, cuts)


def train(docs: DataFrame, labels: DataFrame, per_label: int = PER_LABEL) -> Model:
    lab = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic"))
    lab = lab.filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    picked = hash_sample(lab, "toxic", per_label, 2).collect()
    if not picked:
        return fit([], [])
    sample = small_table(docs.sparkSession, sorted({(r.doc_id, r.toxic) for r in picked}), "doc_id long, _toxic int")
    out = pa.schema([("toxic", pa.int32()), ("words", pa.list_(pa.string()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            yield record(out, b.column(2), [sorted(words(t)) for t in b.column(1).to_pylist()])

    rows = doc_text(docs).join(F.broadcast(sample), "doc_id").select("doc_id", "text", "_toxic").mapInArrow(run, "toxic int, words array<string>").collect()
    rows.sort(key=lambda r: (r.toxic, r.words))
    return fit([set(r.words) for r in rows], [r.toxic for r in rows])


def score(docs: DataFrame, model: Model) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)
    kinds = (pa.int64(), pa.float64(), pa.int32(), pa.float64(), pa.bool_())
    out = pa.schema(list(zip([c.split()[0] for c in SCHEMA.split(", ")], kinds)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            rows = []
            for t in b.column(1).to_pylist():
                p = shared.value.exceed(words(t))
                rows.append((float(p.sum()), int((p >= 0.5).sum()), float(p[0]), bool(p.sum() >= FLAG)))
            yield record(out, b.column(0), *zip(*rows))

    return doc_text(docs).mapInArrow(run, SCHEMA)
