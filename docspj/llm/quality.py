"""Quality score by compression: zstandard dictionaries of good and of bad text.

A text is cut into pieces of 1000 bytes, so that a dictionary matters all through a long text, and each piece is compressed once with
either dictionary. The difference of the summed sizes over the text's bytes, positive where good text's dictionary does better, becomes a
probability by logistic calibration on labelled texts that made no dictionary.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import bounded_sample, held_out, only, slices

PIECE = 1000


@dataclass
class QualityModel:
    bad: bytes
    good: bytes
    raw: bool  # the dictionaries are plain text, as there was too little to train on
    slope: float = 1.0
    offset: float = 0.0
    level: int = 1

    def compressors(self) -> list[zstandard.ZstdCompressor]:
        kind = zstandard.DICT_TYPE_RAWCONTENT if self.raw else zstandard.DICT_TYPE_FULLDICT
        return [zstandard.ZstdCompressor(level=self.level, dict_data=zstandard.ZstdCompressionDict(d, dict_type=kind), write_content_size=False) for d in (self.bad, self.good)]

    def score(self, gains: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.slope * gains + self.offset, -500, 500)))


def gain(text: bytes | None, compressors: list[zstandard.ZstdCompressor]) -> float:
    """Bytes a byte that good text's dictionary saves against bad text's; 0 for an empty text."""
    if not text:
        return 0.0
    bad, good = compressors
    return sum(len(bad.compress(p)) - len(good.compress(p)) for p in (text[k : k + PIECE] for k in range(0, len(text), PIECE))) / len(text)


def _dictionaries(samples: dict[int, list[bytes]], size: int) -> QualityModel:
    try:
        return QualityModel(*[zstandard.train_dictionary(size, samples[q]).as_bytes() for q in (0, 1)], raw=False)
    except zstandard.ZstdError:
        return QualityModel(*[b"\n".join(samples[q])[:size] for q in (0, 1)], raw=True)


def _calibrate(model: QualityModel, gains: np.ndarray, labels: np.ndarray, weights: np.ndarray) -> None:
    """Weighted logistic regression by Newton steps on the standardised gain, lightly regularised."""
    centre, spread = gains.mean(), gains.std() or 1.0
    x = np.column_stack([(gains - centre) / spread, np.ones(len(gains))])
    beta = np.zeros(2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        slope = x.T @ (weights * (p - labels)) + 1e-3 * beta
        step = np.linalg.solve((x * (weights * p * (1 - p))[:, None]).T @ x + np.eye(2) * 1e-3, slope)
        beta -= step
        if np.abs(step).max() < 1e-9:
            break
    model.slope, model.offset = float(beta[0] / spread), float(beta[1] - beta[0] * centre / spread)


def train_quality_model(docs: DataFrame, labels: DataFrame, per_class: int = 1500, pieces: int = 6, dictionary_bytes: int = 112 << 10, seed: int = 7) -> QualityModel | None:
    """Learn from documents(doc_id, text) and labels(doc_id, quality) that are not held out.

    The sample is bounded: `per_class` documents of each label, of least seeded hash, give `pieces` evenly spaced pieces each to the
    dictionaries, and as many others calibrate with whole texts. An id with contradicting labels teaches nothing. None if a label is missing.
    """
    docs = only(docs, ["doc_id", "text"]).where("doc_id is not null and text is not null")
    clear = only(labels, ["doc_id", "quality"]).where(F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id")))
    clear = clear.groupBy("doc_id").agg(F.min("quality").alias("quality"), F.max("quality").alias("other")).where("quality = other").drop("other")
    counts = {r[0]: r[1] for r in clear.groupBy("quality").count().collect()}
    if set(counts) != {0, 1}:
        return None
    part = F.pmod(F.xxhash64(F.lit(seed), F.col("doc_id").cast("string")), F.lit(2))
    chosen = [[bounded_sample(clear.where((F.col("quality") == q) & (part == k)), "doc_id", per_class, seed) for q in (0, 1)] for k in (0, 1)]
    taught, checked = (docs.join(F.broadcast(c[0].unionByName(c[1])), "doc_id").select("doc_id", "text", "quality") for c in chosen)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            ids, labels, found = [], [], []
            for key, text, q in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()).to_pylist(), batch.column(2).to_pylist(), strict=True):
                starts = range(0, len(text), PIECE)
                for k in sorted({i * len(starts) // pieces for i in range(pieces)} if len(starts) > pieces else range(len(starts))):
                    ids.append(key), labels.append(q), found.append(text[starts[k] : starts[k] + PIECE])
            yield pa.RecordBatch.from_arrays([pa.array(ids, batch.column(0).type), pa.array(labels, pa.int32()), pa.array(found, pa.binary())], names=["doc_id", "quality", "piece"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    samples: dict[int, list[bytes]] = {0: [], 1: []}
    for r in sorted(taught.mapInArrow(cut, f"doc_id {kind}, quality int, piece binary").collect(), key=lambda r: (r[0], r[1])):
        samples[r.quality].append(bytes(r.piece))
    if not all(samples.values()):
        return None
    model = _dictionaries(samples, dictionary_bytes)
    rated = _gains(checked, model, "quality int").collect()
    if {r.quality for r in rated} == {0, 1}:
        given = np.array([r.quality for r in rated])
        weights = np.where(given == 1, counts[1] / (given == 1).sum(), counts[0] / (given == 0).sum())
        _calibrate(model, np.array([r.gain for r in rated]), given, weights / weights.mean())
    return model


def _gains(docs: DataFrame, model: QualityModel, extra: str = "") -> DataFrame:
    """(doc_id, extra column, gain) of docs(doc_id, text, extra column)."""

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compressors = model.compressors()
        for batch in slices(batches):
            found = [gain(t.as_py(), compressors) for t in batch.column(1).cast(pa.binary())]
            rest = [batch.column(2).cast(pa.int32())] if extra else []
            yield pa.RecordBatch.from_arrays([batch.column(0), *rest, pa.array(found, pa.float64())], names=["doc_id", *([extra.split()[0]] if extra else []), "gain"])

    return docs.mapInArrow(of, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}{', ' + extra if extra else ''}, gain double")


def score_quality(docs: DataFrame, model: QualityModel | None, threshold: float = 0.7) -> DataFrame:
    """(doc_id, score, predicted) of each row's whole text: the calibrated probability of label 1, and whether it reaches the threshold.

    Null and empty texts have gain 0; without a model the score is 0.5. Repeated rows score alike. The text alone is read.
    """
    docs = only(docs, ["doc_id", "text"])
    if model is None:
        scored = docs.select("doc_id", F.lit(0.5).alias("score"))
    else:
        logit = F.greatest(F.lit(-500.0), F.least(F.lit(500.0), F.col("gain") * model.slope + model.offset))
        scored = _gains(docs, model).select("doc_id", (1 / (1 + F.exp(-logit))).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
