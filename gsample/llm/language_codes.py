"""Language identification by error-correcting output codes.

Every language has a codeword; a binary classifier over hashed letter n-grams predicts
each bit.  Decoding adds up, for each codeword, the logistic losses that the classifiers'
margins have against its bits, each bit weighted by how well its classifier did in
training; the least loss wins.  A text whose two best codewords are close is flagged.

With up to seven languages the code has every distinct split of the languages; with more,
random splits are drawn and the set with the largest smallest distance is kept.

The fit is on at most about ``per_language`` documents of each language (a documented
bound), the prediction on every whole text.  Defined results: ``und`` with score 0 for a
null text or one without a letter, and for all if nothing was learned; one learned
language gets score 1; other columns are not read; null ids are answered, not learned from.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import packed

DIMENSIONS = 4096
UNDETERMINED = "und"


def _letter_table() -> np.ndarray:
    """Code point to its lower-case letter, or to a space if it is no letter."""
    out = np.full(0x110000, 32, np.uint32)
    for c in itertools.chain(range(0xD800), range(0xE000, 0x110000)):
        ch = chr(c)
        if ch.isalpha():
            out[c] = ord(ch.lower()[0])
    return out


_letters: list[np.ndarray] = []


def features(text: str | None) -> np.ndarray | None:
    """Square roots of the shares of hashed 1-, 2- and 3-grams; None without a letter."""
    if not text:
        return None
    if not _letters:
        _letters.append(_letter_table())
    c = _letters[0][np.frombuffer(text.encode("utf-32-le"), np.uint32)]
    known = c != 32
    if not known.any():
        return None
    keep = known.copy()
    keep[1:] |= known[:-1]  # one space after each word
    c = np.concatenate([[np.uint32(32)], c[keep], [np.uint32(32)]]).astype(np.uint32)
    h1 = c * np.uint32(2654435761)
    h2 = (h1[:-1] ^ np.uint32(0x9E3779B9)) * np.uint32(2246822519) + c[1:] * np.uint32(3266489917)
    h3 = (h2[:-1] ^ (h2[:-1] >> np.uint32(15))) * np.uint32(668265263) + c[2:] * np.uint32(374761393)
    counts = np.zeros(DIMENSIONS, np.float32)
    for h in (h1, h2, h3):
        h ^= h >> np.uint32(13)
        counts += np.bincount(((h * np.uint32(2246822519)) >> np.uint32(20)).astype(np.int64), minlength=DIMENSIONS).astype(np.float32) / max(len(h), 1)
    return np.sqrt(counts / 3)


def codewords(classes: int, seed: int = 0) -> np.ndarray:
    """classes x bits of +1 and -1; every column splits the classes, no two alike."""
    if classes <= 1:
        return np.ones((classes, 1), np.float32)
    if classes <= 7:
        columns = [[1, *(1 if bits >> k & 1 else -1 for k in range(classes - 1))] for bits in range(2 ** (classes - 1) - 1)]
        return np.array(columns, np.float32).T
    rng, bits = np.random.default_rng(seed), int(np.ceil(10 * np.log2(classes)))
    best, best_distance = None, -1
    for _ in range(200):
        m = rng.choice(np.array([-1, 1], np.float32), (classes, bits))
        distance = ((bits - m @ m.T) / 2 + np.eye(classes) * bits).min()
        if distance > best_distance and (abs(m.sum(0)) < classes).all():
            best, best_distance = m, distance
    return best


class CodeModel:
    def __init__(self, languages: list[str], x: np.ndarray, y: np.ndarray, steps: int = 200, penalty: float = 1e-4):
        self.languages, self.code = languages, codewords(len(languages))
        targets = self.code[y]
        weight = (1 / np.bincount(y, minlength=len(languages)))[y][:, None].astype(np.float32)
        weight /= weight.sum()
        w, b = np.zeros((x.shape[1], self.code.shape[1]), np.float32), np.zeros(self.code.shape[1], np.float32)
        m, v, rate = np.zeros_like(w), np.zeros_like(w), 0.5
        for t in range(1, steps + 1):
            z = x @ w + b
            g = -targets / (1 + np.exp(np.clip(targets * z, -30, 30))) * weight
            gw, gb = x.T @ g + penalty * w, g.sum(0)
            m, v = 0.9 * m + 0.1 * gw, 0.99 * v + 0.01 * gw * gw
            w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-6)
            b -= 2 * gb
        self.w, self.b = w, b
        z = targets * (x @ w + b)
        self.trust = np.maximum((z > 0).astype(np.float32).mean(0) * 2 - 1, 0.05)
        self.trust /= self.trust.sum()

    def decode(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Best language, its probability, and its lead over the next in weighted loss."""
        z = x @ self.w + self.b
        losses = np.stack([(np.logaddexp(0, -z * row) * self.trust).sum(1) for row in self.code], 1)
        p = np.exp(-(losses - losses.min(1, keepdims=True)) * self.code.shape[1])
        p /= p.sum(1, keepdims=True)
        two = np.sort(losses, 1)
        lead = two[:, 1] - two[:, 0] if losses.shape[1] > 1 else np.full(len(x), np.inf)
        best = losses.argmin(1)
        return best, p[np.arange(len(x)), best], lead


def fit(docs: DataFrame, learn, id: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = 500) -> CodeModel | None:
    """Fits on about ``per_language`` rows of each language among those where ``learn`` holds."""
    known = docs.where(learn & F.col(lang).isNotNull()).select(F.col(id).alias("i"), F.col(lang).alias("l"), F.col(text).alias("t"))
    counts = {r["l"]: r["count"] for r in known.groupBy("l").count().collect()}
    if not counts:
        return None
    share = F.create_map(*(F.lit(v) for k, n in counts.items() for v in (k, int(min(1.0, 1.3 * per_language / n) * (1 << 30)))))
    few = known.where(F.pmod(F.xxhash64(F.lit(5), "i"), F.lit(1 << 30)) < share[F.col("l")])
    few = few.withColumn("k", F.row_number().over(Window.partitionBy("l").orderBy(F.xxhash64("i"), "i"))).where(F.col("k") <= per_language)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(k, f.astype(np.float16).tobytes()) for k, t in enumerate(batch.column(1).to_pylist()) if (f := features(t)) is not None]
            yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array([k for k, _ in rows], pa.int64())), pa.array([f for _, f in rows], pa.binary())], names=["l", "f"])

    rows = few.select("l", "t").mapInArrow(run, "l string, f binary").toArrow()
    if not rows.num_rows:
        return None
    # whole arrays: thousands of small objects leave the driver's Python with their memory
    flat = packed.read(rows.column("f"), np.float16).reshape(-1, DIMENSIONS)
    languages, y = np.unique(rows.column("l").to_numpy(zero_copy_only=False).astype(str), return_inverse=True)
    del rows
    order = np.lexsort((np.argsort(np.argsort(flat.view(f"S{2 * DIMENSIONS}").ravel(), kind="stable")), y))
    return CodeModel(languages.tolist(), flat[order].astype(np.float32), y[order])


def predict(docs: DataFrame, model: CodeModel | None, id: str = "doc_id", text: str = "text", close: float = 0.05) -> DataFrame:
    """(id, lang_pred, score, ambiguous) for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                found = [features(t) for t in part.column(1).to_pylist()]
                some = [k for k, f in enumerate(found) if f is not None] if m else []
                names, scores, doubt = [UNDETERMINED] * len(found), np.zeros(len(found)), np.ones(len(found), bool)
                if some:
                    best, p, lead = m.decode(np.stack([found[k] for k in some]))
                    scores[some], doubt[some] = p, lead < close
                    for k, b in zip(some, best, strict=True):
                        names[k] = m.languages[b]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(names), pa.array(scores, pa.float64()), pa.array(doubt)], names=[id, "lang_pred", "score", "ambiguous"])

    kind = dict(docs.dtypes)[id]
    return docs.select(id, text).mapInArrow(run, f"`{id}` {kind}, lang_pred string, score double, ambiguous boolean")


def drop_undetermined(docs: DataFrame, model: CodeModel | None, text: str = "text", close: float = 0.05, least: float = 0.4) -> DataFrame:
    """The rows, with all columns, that have a language: those of ``und`` go, and ambiguous ones whose best codeword is unlikely."""
    shared, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for k in range(0, batch.num_rows, 512):
                part = batch.slice(k, 512)
                found = [features(t) for t in part.column(at).to_pylist()]
                keep = np.array([f is not None for f in found])
                if m and keep.any():
                    _, p, lead = m.decode(np.stack([f for f in found if f is not None]))
                    keep[keep] = (lead >= close) | (p >= least)
                yield part.filter(pa.array(keep))

    return docs.mapInArrow(run, docs.schema)
