"""Language ID: averaged hashed subword embeddings under a linear softmax, trained by stochastic gradient descent in numpy.

Subwords are runs of two to four characters of a lowered text in which everything but letters is a word edge; none reaches
over an edge. Each hashes to one of 2**15 rows of an embedding table. A text's logits are its rows' mean times the output
layer; the product of the two matrices is what tasks get (2**15 numbers a language). Confidence is calibrated by a
temperature, and texts under a calibrated confidence are rejected.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import held_out, keep_rows, only, slices

UNKNOWN = "und"
_BITS = 15
_FACTORS = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], np.uint32)


def _letters() -> np.ndarray:
    return np.fromiter((chr(c).isalpha() for c in range(0x10000)), bool, 0x10000)


def subwords(texts: list[str], is_letter: np.ndarray) -> Iterator[tuple[int, list[tuple[np.ndarray, np.ndarray]]]]:
    """For runs of texts: the first one's place, and for each subword length the rows hit with the place of each in its run."""
    first = 0
    while first < len(texts):
        last, size = first, 0
        while last < len(texts) and (last == first or size + len(texts[last]) <= 1 << 19):
            size += len(texts[last]) + 1
            last += 1
        part = [t.lower() for t in texts[first:last]]
        codes = np.frombuffer(("\n" + "\n".join(part) + "\n").encode("utf-32-le", "surrogatepass"), np.uint32)
        alpha = np.zeros(len(codes), bool)
        low = codes < 0x10000
        alpha[low] = is_letter[codes[low]]
        if not low.all():
            alpha[~low] = [chr(c).isalpha() for c in codes[~low]]
        codes = np.where(alpha, codes, np.uint32(0))
        owner = np.repeat(np.arange(len(part), dtype=np.int32), [len(t) + 1 for t in part])
        owner = np.append(owner, np.int32(len(part) - 1))
        found, run, inner = [], codes * _FACTORS[0], alpha
        for n in range(2, 5):
            run = run[:-1] + codes[n - 1 :] * _FACTORS[n - 1]
            inside = alpha[: len(run)] | alpha[1 : len(run) + 1] if n == 2 else inner
            hit = np.flatnonzero(inside)
            mixed = run[hit] ^ (run[hit] >> np.uint32(15))
            found.append((((mixed * np.uint32(0x2C1B3C6D)) ^ np.uint32(n * 0x9E37)) >> np.uint32(32 - _BITS), owner[hit]))
            if n < 4:
                inner = alpha[1 : len(run)] if n == 2 else inner[:-1] & alpha[2 : len(run) + 1]
        yield first, found
        first = last


@dataclass
class LanguageModel:
    languages: list[str]
    table: np.ndarray  # rows x languages, float32: embedding times output layer
    bias: np.ndarray
    temperature: float
    reject_below: float


def predict(model: LanguageModel, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
    """Language, calibrated confidence and whether the text is rejected. Null and texts without letters: und, 0, rejected."""
    is_letter, k = _letters(), len(model.languages)
    sums, hits = np.zeros((len(texts), k)), np.zeros(len(texts))
    for first, found in subwords([t or "" for t in texts], is_letter):
        for rows, owner in found:
            if k:
                edges = np.flatnonzero(np.diff(owner, prepend=-1))
                if len(edges):
                    sums[first + owner[edges]] += np.add.reduceat(model.table[rows], edges, axis=0, dtype=np.float64)
            np.add.at(hits, first + np.unique(owner), np.bincount(owner)[np.unique(owner)])
    if not k:
        return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.ones(len(texts), bool)
    logits = (sums / np.maximum(hits, 1)[:, None] + model.bias) / model.temperature
    chance = np.exp(logits - logits.max(axis=1, keepdims=True))
    chance /= chance.sum(axis=1, keepdims=True)
    best = chance.argmax(axis=1)
    score = np.where(hits > 0, chance[np.arange(len(texts)), best], 0.0)
    names = [model.languages[b] if h else UNKNOWN for b, h in zip(best.tolist(), hits.tolist(), strict=True)]
    return names, score, (hits == 0) | (score < model.reject_below)


def _fit(samples: list[tuple[int, np.ndarray, np.ndarray]], languages: list[str], dim: int, epochs: int, seed: int) -> LanguageModel:
    rng = np.random.default_rng(seed)
    embed = rng.uniform(-1 / dim, 1 / dim, (1 << _BITS, dim))
    out, bias = np.zeros((dim, len(languages))), np.zeros(len(languages))
    checks, learn = samples[::5], [s for i, s in enumerate(samples) if i % 5] or samples
    steps, done = epochs * len(learn), 0
    for _ in range(epochs):
        for i in rng.permutation(len(learn)):
            label, rows, weight = learn[i]
            hidden = weight @ embed[rows]
            logits = hidden @ out + bias
            slope = np.exp(logits - logits.max())
            slope /= slope.sum()
            slope[label] -= 1
            rate = 0.5 * (1 - done / steps)
            back = out @ slope
            out -= rate * np.outer(hidden, slope)
            bias -= 0.1 * rate * slope
            embed[rows] -= rate * len(rows) ** 0.5 * weight[:, None] * back
            done += 1
    table = embed @ out
    logits = np.array([w @ table[r] + bias for _, r, w in checks])
    truth = np.array([s[0] for s in checks])

    def chances(temperature: float) -> np.ndarray:
        e = np.exp((logits - logits.max(axis=1, keepdims=True)) / temperature)
        return e / e.sum(axis=1, keepdims=True)

    loss = {t: -np.log(chances(t)[np.arange(len(truth)), truth] + 1e-12).mean() for t in np.geomspace(0.5, 20, 60)}
    temperature = min(loss, key=loss.get)
    right = chances(temperature)
    right = right.max(axis=1)[right.argmax(axis=1) == truth]
    return LanguageModel(languages, table.astype(np.float32), bias, float(temperature), float(min(0.5, np.quantile(right, 0.002))) if len(right) else 0.0)


def train_language_model(docs: DataFrame, per_language: int = 500, most_languages: int = 400, dim: int = 12, epochs: int = 6, seed: int = 8) -> LanguageModel:
    """Learn from (doc_id, text, lang) of rows that are not held out, have a language and a letter.

    The sample is bounded: about `per_language` whole documents of each of the `most_languages` commonest languages, those of
    least seeded hash; a task sends the driver at most 2**15 counts a document. Every fifth sampled document only calibrates.
    Nothing to learn from: a model that answers `und`.
    """
    docs = only(docs, ["doc_id", "text", "lang"]).where(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~held_out(F.col("doc_id")))
    counts = {r[0]: r[1] for r in docs.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most_languages).collect()}
    if not counts:
        return LanguageModel([], np.zeros((1 << _BITS, 0), np.float32), np.zeros(0), 1.0, 0.0)
    languages = sorted(counts)
    share = F.create_map(*[F.lit(x) for lang in languages for x in (lang, min(1.0, per_language / counts[lang]))])
    place = F.pmod(F.xxhash64(F.lit(seed), F.col("doc_id").cast("string")), F.lit(1 << 30)) / float(1 << 30)
    chosen = docs.where(place < F.try_element_at(share, F.col("lang")))

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        is_letter = _letters()
        for batch in slices(batches):
            texts = batch.column(1).to_pylist()
            rows: list[np.ndarray | None] = [None] * len(texts)
            for first, found in subwords(texts, is_letter):
                hit, owner = (np.concatenate([f[k] for f in found]) for k in (0, 1))
                order = np.argsort(owner, kind="stable")
                for i, part in enumerate(np.split(hit[order], np.searchsorted(owner[order], np.arange(1, owner.max() + 1)) if len(owner) else [])):
                    rows[first + i] = part
            pairs = [np.unique(r, return_counts=True) if r is not None else (np.empty(0), np.empty(0)) for r in rows]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array([p[0].astype("<u2").tobytes() for p in pairs], pa.binary()), pa.array([p[1].astype("<u4").tobytes() for p in pairs], pa.binary())],
                names=["doc_id", "lang", "rows", "counts"],
            )

    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, lang string, rows binary, counts binary"
    samples = []
    for r in sorted(chosen.select("doc_id", "text", "lang").mapInArrow(of, schema).collect(), key=lambda r: (r.doc_id, r.lang, bytes(r.rows))):
        rows, counts_ = np.frombuffer(r.rows, "<u2").astype(np.int64), np.frombuffer(r.counts, "<u4")
        if len(rows):
            samples.append((languages.index(r.lang), rows, counts_ / counts_.sum()))
    if not samples:
        return LanguageModel([], np.zeros((1 << _BITS, 0), np.float32), np.zeros(0), 1.0, 0.0)
    return _fit([samples[i] for i in np.random.default_rng(seed).permutation(len(samples))], languages, dim, epochs, seed)


def identify(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """(doc_id, lang_pred, score, rejected) of each row's whole text; the text alone is read."""
    docs = only(docs, ["doc_id", "text"])

    def of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            names, score, rejected = predict(model, batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(names, pa.string()), pa.array(score, pa.float64()), pa.array(rejected, pa.bool_())], names=["doc_id", "lang_pred", "score", "rejected"])

    return docs.mapInArrow(of, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, lang_pred string, score double, rejected boolean")


def keep_identified(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """The rows, with all their columns, whose language the model does not reject."""
    return keep_rows(docs, "text", lambda texts: (~predict(model, texts)[2]).tolist())
