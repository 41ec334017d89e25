"""Toxicity from confirmed toxic examples and unlabelled text by non-negative PU learning.

No clean example is needed.  With p the share of toxic text, the risk of a classifier is
p * (its loss on the confirmed ones as toxic) plus its loss on unlabelled text as clean
less p * (its loss on the confirmed ones as clean).  The second part estimates the risk
on clean text, which cannot be negative; where a step drives it below zero, the step
undoes the overfit instead.  The classifiers are linear, in numpy, over counts of words
and word beginnings which confirmed examples use more than unlabelled text does; a few
are trained from different starts and their margins averaged.

The fit uses about ``positives`` confirmed rows and ``unlabelled`` others (documented
bounds).  The score covers every whole text.  Defined results: a null, empty or wordless
text gets the score of no evidence; without a confirmed example all scores are 0; null
ids are scored and not learned from; labels, language, source and id are never inputs.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.materialize import materialize
from .folds import bounded_sample

WORD = re.compile(r"[^\W\d_]+")
#: Lengths of word beginnings that count as features beside whole words.
BEGINNINGS = (4, 5, 6, 7)


def parts(word: str) -> list[str]:
    """A word's features: itself, and its beginnings marked by a hyphen."""
    return [word, *(word[:n] + "-" for n in BEGINNINGS if len(word) >= n)]


class PuModel:
    def __init__(self, names: list[str], positive: np.ndarray, unlabelled: np.ndarray, prior: float, members: int = 3, steps: int = 400):
        """Rows are counts of ``names`` with the number of words last."""
        self.index = {n: k for k, n in enumerate(names)}
        self.memo: dict[str, tuple[int, ...]] = {}
        p, u = self.shape(positive), self.shape(unlabelled)
        self.scale = np.maximum(np.concatenate([p, u]).std(0), 0.3)  # a rare feature gains no weight by being rare
        self.scale[-1] = 1
        p, u = p / self.scale, u / self.scale
        self.w = np.mean([self._train(p, u, prior, steps, seed) for seed in range(members)], 0)

    @staticmethod
    def shape(counts: np.ndarray) -> np.ndarray:
        """Dampened counts, how dense the evidence is, and a constant."""
        c, n = counts[:, :-1].astype(np.float64), counts[:, -1:].astype(np.float64)
        every = c.sum(1, keepdims=True)
        return np.concatenate([np.log1p(c), np.log1p(every), np.log1p(100 * every / np.maximum(n, 20)), np.log1p(n) / 10, np.ones_like(n)], 1)

    @staticmethod
    def _train(p: np.ndarray, u: np.ndarray, prior: float, steps: int, seed: int, penalty: float = 2e-3) -> np.ndarray:
        rng = np.random.default_rng(seed)
        w = rng.normal(0, 0.01, p.shape[1])
        m, v = np.zeros_like(w), np.zeros_like(w)
        for t in range(1, steps + 1):
            i, j = rng.integers(0, len(p), min(len(p), 1024)), rng.integers(0, len(u), min(len(u), 2048))
            sp, su = 1 / (1 + np.exp(-np.clip(p[i] @ w, -30, 30))), 1 / (1 + np.exp(-np.clip(u[j] @ w, -30, 30)))
            # sigmoid losses: 1 - s as toxic, s as clean
            clean = su.mean() - prior * sp.mean()
            d_pos = p[i].T @ (sp * (1 - sp)) / len(i)
            d_clean = u[j].T @ (su * (1 - su)) / len(j) - prior * d_pos
            g = -prior * d_pos + d_clean if clean >= 0 else -d_clean
            g = g + penalty * np.append(w[:-1], 0) * (1 - t / (2 * steps))
            m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
            w = w - 0.05 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
        return w

    def count(self, text: str | None) -> np.ndarray:
        words = WORD.findall((text or "").lower())
        out = np.zeros(len(self.index) + 1, np.float32)
        out[-1] = len(words)
        memo = self.memo
        for word, n in Counter(words).items():
            known = memo.get(word)
            if known is None:
                if len(memo) > 100_000:
                    memo.clear()
                known = memo[word] = tuple(self.index[f] for f in parts(word) if f in self.index)
            for k in known:
                out[k] += n
        return out

    def score(self, counts: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.shape(counts) / self.scale @ self.w, -30, 30)))

    def __getstate__(self):
        return self.__dict__ | {"memo": {}}


def _pick_features(sample: DataFrame, positives: int, unlabelled: int, most: int) -> list[str]:
    """Words and beginnings by how much more often confirmed examples hold them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[bool, Counter] = {True: Counter(), False: Counter()}
            for confirmed, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                seen[confirmed].update({f for w in set(WORD.findall((text or "").lower())) for f in parts(w)})
            p, u = seen[True], seen[False]
            keys = [*p, *(k for k, n in u.items() if k not in p and n > 1)]
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.string()), pa.array([p[k] for k in keys], pa.int64()), pa.array([u[k] for k in keys], pa.int64())], names=["f", "p", "u"])

    counted = sample.select("confirmed", "text").mapInArrow(run, "f string, p bigint, u bigint").groupBy("f").agg(F.sum("p").alias("p"), F.sum("u").alias("u"))
    a, b = (F.col("p") + 0.5) / (positives + 1), (F.col("u") + 0.5) / (unlabelled + 1)
    lead = F.log(a / b) * (a - b)  # a share's lead, by its reliability
    few = counted.where((F.col("p") >= max(3, positives // 200)) & (a > 2 * b)).orderBy(lead.desc(), "f").limit(most)
    return [r["f"] for r in few.collect()]


def fit(docs: DataFrame, labels: DataFrame, learn: Column, id: str = "doc_id", text: str = "text", label: str = "toxic", prior: float | None = None, positives: int = 3000, unlabelled: int = 6000, candidates: int = 400, features: int = 100) -> PuModel | None:
    """Learns from rows where ``learn`` (over ``id``) holds; ``prior``: the share of toxic text, else the labels'."""
    marks = labels.where(learn & F.col(label).isNotNull()).select(id, label)
    n = {r[label]: r["count"] for r in marks.groupBy(label).count().collect()}
    if not n.get(1):
        return None
    share = prior if prior is not None else min(0.9, max(0.001, n[1] / sum(n.values()) if len(n) > 1 else 0.1))
    rows = docs.where(learn).select(id, F.col(text).alias("text"))
    some = bounded_sample(marks.where(F.col(label) == 1).select(id).distinct(), id, positives, 11, n[1])
    marked = F.broadcast(some.withColumn("confirmed", F.lit(True)))  # bounded by ``positives``
    other = F.pmod(F.xxhash64(F.lit(12), F.col(id)), F.lit(1 << 30)) < int(min(1.0, unlabelled / max(docs.count(), 1)) * (1 << 30))
    taken = rows.withColumn("other", other).join(marked, id, "left").where("confirmed or other")
    taken = materialize(taken.select(F.coalesce("confirmed", F.lit(False)).alias("confirmed"), "text"), "pu").repartition(12)
    sizes = {r["confirmed"]: r["count"] for r in taken.groupBy("confirmed").count().collect()}
    if not sizes.get(True) or not sizes.get(False):
        return None
    names = _pick_features(taken, sizes[True], sizes[False], candidates)
    blank = PuModel.__new__(PuModel)
    blank.index, blank.memo = {f: k for k, f in enumerate(names)}, {}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([blank.count(t).tobytes() for t in batch.column(1).to_pylist()], pa.binary())], names=["c", "v"])

    rows_ = sorted((r["c"], bytes(r["v"])) for r in taken.select("confirmed", "text").mapInArrow(run, "c boolean, v binary").collect())
    x, c = np.stack([np.frombuffer(v, np.float32) for _, v in rows_]), np.array([k for k, _ in rows_])
    own = list({x[:, k].tobytes(): k for k in reversed(range(len(names)))}.values())[::-1][:features]  # one of those that always go together
    x = x[:, [*own, len(names)]]
    return PuModel([names[k] for k in own], x[c], x[~c], share)


def score(docs: DataFrame, model: PuModel | None, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, score) for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = part.column(1).to_pylist()
                scores = m.score(np.stack([m.count(t) for t in texts])) if m else np.zeros(len(texts))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(scores, pa.float64())], names=[id, "score"])

    kind = dict(docs.dtypes)[id]
    return docs.select(id, text).mapInArrow(run, f"`{id}` {kind}, score double")


def drop_toxic(docs: DataFrame, model: PuModel | None, text: str = "text", threshold: float = 0.5) -> DataFrame:
    """The rows, with all columns, that score below ``threshold``."""
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                if m:
                    part = part.filter(pa.array(m.score(np.stack([m.count(t) for t in part.column(at).to_pylist()])) < threshold))
                yield part

    return docs.mapInArrow(run, docs.schema)
