"""Benchmark passages in documents: CGK random walks, bit-sampling LSH over item-sized windows, exact edit verification.

Texts are lowered and ASCII punctuation counts as white space; the unit of an edit is a word. An item is found in a document if
some stretch of the document lies within `edit_share` of the item's words in edits. A random walk reads a window word by
word; at each of three steps a word, a hash of step and word says whether the walk moves on, so few edits leave most of the
walk's output unchanged. Each repetition samples a few output places; equal samples make a window and an item of its length a
candidate. The number of repetitions is the least that finds the target share of seeded edited copies of the items themselves,
at the full edit allowance. Documents and windows that hold too few of an item's runs of three words to lie within the
allowance are passed over first; this loses nothing (an edit touches at most three such runs).

Items of fewer words than `least_words` leave no room for edits that still mean the same: they are found where their words stand
one after another unchanged.
"""

from __future__ import annotations

import string
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from docspj.llm.common import keep_rows, only, slices
from docspj.llm.shingles import _PLACE, mix, word_hashes

_BLANKED = bytes.maketrans(string.punctuation.encode(), b" " * len(string.punctuation))
_WALK = 3
#: Edited copies of a length's items on which its recall is measured, and windows that are walked at once.
_TRIALS, _WINDOWS, _MOST_REPETITIONS = 200, 2048, 4096


def normal_words(text: str | None) -> np.ndarray:
    return word_hashes((text or "").lower().encode("utf-8", "surrogatepass").translate(_BLANKED))[0]


def _runs(words: np.ndarray) -> np.ndarray:
    return mix(words[:-2] * _PLACE[0] + words[1:-1] * _PLACE[1] + words[2:] * _PLACE[4]) if len(words) > 2 else np.empty(0, np.uint64)


def _grams(words: np.ndarray, n: int) -> np.ndarray:
    """A hash of each n words that follow one another."""
    count = max(0, len(words) - n + 1)
    out = np.full(count, np.uint64(n))
    for k in range(n):
        out = mix(out * _PLACE[3] + words[k : k + count])
    return out


def walk_samples(windows: np.ndarray, places: np.ndarray, seed: int) -> np.ndarray:
    """Keys (repetition, window) of windows (window, word): the walk's output at each repetition's places, hashed."""
    count, n = windows.shape
    reps, taken = places.shape
    padded = np.concatenate([windows, np.zeros((count, 1), np.uint64)], axis=1)
    row, at = np.arange(count)[None, :], np.zeros((reps, count), np.int64)
    salt = mix(np.arange(reps, dtype=np.uint64)[:, None] + np.uint64(seed * 1_000_003))
    keys = np.tile(salt, (1, count))
    for step in range(_WALK * n):
        word = padded[row, at]
        for t in range(taken):
            here = np.flatnonzero(places[:, t] == step)
            if len(here):
                keys[here] = mix(keys[here] * _PLACE[2] + word[here] + np.uint64(t + 1))
        coin = ((word + salt) * (_PLACE[3] + np.uint64(2 * step))) >> np.uint64(63)
        at = np.minimum(at + coin.astype(np.int64), n)
    return keys


def edited(words: np.ndarray, edits: int, rng: np.random.Generator) -> np.ndarray:
    out = words.tolist()
    for _ in range(edits):
        at, kind = int(rng.integers(0, max(1, len(out)))), int(rng.integers(0, 3))
        new = int(rng.integers(1, 2**63))
        if kind == 0 and len(out) > 1:
            del out[at]
        elif kind == 1:
            out.insert(at, new)
        else:
            out[at] = new
    return np.array(out, np.uint64)


def best_stretch(item: list[int], text: list[int]) -> tuple[int, int, int]:
    """Least edits that make the item a stretch of text, with the stretch's first place and end; earliest end on ties."""
    cost, begin = [0] * (len(text) + 1), list(range(len(text) + 1))
    for i, word in enumerate(item, 1):
        new, source = [i], [0]
        for j, other in enumerate(text, 1):
            best, here = cost[j - 1] + (word != other), begin[j - 1]
            if cost[j] + 1 < best:
                best, here = cost[j] + 1, begin[j]
            if new[j - 1] + 1 < best:
                best, here = new[j - 1] + 1, source[j - 1]
            new.append(best), source.append(here)
        cost, begin = new, source
    end = min(range(len(cost)), key=cost.__getitem__)
    return cost[end], begin[end], end


@dataclass
class BenchmarkIndex:
    """Items by length in words, with their samples. Built on the driver from at most `most_bytes` of benchmark text."""

    edit_share: float
    seed: int
    ids: list[int] = field(default_factory=list)
    words: list[list[int]] = field(default_factory=list)
    by_length: dict = field(default_factory=dict)  # n: (places, sorted keys, item of each key)
    runs: np.ndarray = field(default_factory=lambda: np.empty(0, np.uint64))
    holders: tuple = ()  # of each run in `runs`: where its items begin in the second array
    lengths: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))
    rooms: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))
    distinct: np.ndarray = field(default_factory=lambda: np.empty(0, np.int64))
    bitmap: np.ndarray = field(default_factory=lambda: np.zeros(1, bool))
    short: dict = field(default_factory=dict)  # n: (sorted hashes, id of each) of items of n words, too few for edits
    recall: float = 1.0  # of the edited copies that the repetitions were chosen on

    def allowance(self, n: int) -> int:
        return int(self.edit_share * n)


def build_index(items: list[tuple[int, str]], edit_share: float = 0.2, least_words: int = 8, sampled: int = 3, recall: float = 0.995, seed: int = 10) -> BenchmarkIndex:
    """items: (id, text). Items without an id, or without words, are left out; those of fewer than `least_words` words are found unedited alone.

    Repetitions are doubled until `recall` of each length's edited copies are found; a length that stays below it raises.
    """
    index, rng = BenchmarkIndex(edit_share, seed), np.random.default_rng(seed)
    for key, text in sorted((i for i in items if i[0] is not None), key=lambda i: (i[0], i[1] or "")):
        words = normal_words(text)
        if len(words) >= least_words:
            index.ids.append(int(key)), index.words.append(words.tolist())
        elif len(words):
            index.short.setdefault(len(words), []).append((int(_grams(words, len(words))[0]), int(key)))
    for n, pairs in index.short.items():
        pairs.sort()
        index.short[n] = (np.array([h for h, _ in pairs], np.uint64), [key for _, key in pairs])
    if not index.ids:
        return index
    own = [np.unique(_runs(np.array(w, np.uint64))) for w in index.words]
    index.lengths = np.array([len(w) for w in index.words])
    index.rooms = np.array([index.allowance(len(w)) for w in index.words])
    index.distinct = np.array([len(x) for x in own])
    flat, item = np.concatenate(own), np.repeat(np.arange(len(own)), index.distinct)
    order = np.argsort(flat, kind="stable")
    index.runs, starts = np.unique(flat[order], return_index=True)
    index.holders = (np.append(starts, len(flat)), item[order])
    bits = max(16, int(len(index.runs) * 16).bit_length())
    index.bitmap = np.zeros(1 << bits, bool)
    index.bitmap[(index.runs >> np.uint64(64 - bits)).astype(np.int64)] = True
    lengths: dict[int, list[int]] = {}
    for at, words in enumerate(index.words):
        lengths.setdefault(len(words), []).append(at)
    found = []
    for n, members in lengths.items():
        whole = np.array([index.words[m] for m in members], np.uint64)
        trials = members * -(-_TRIALS // len(members))
        copies = np.zeros((len(trials), n), np.uint64)
        for t, m in enumerate(trials):
            copy = edited(np.array(index.words[m], np.uint64), index.allowance(n), rng)[:n]
            copies[t, : len(copy)] = copy
        reps, hit = 8, 0.0
        while hit < recall:
            reps *= 2
            if reps > _MOST_REPETITIONS:
                raise ValueError(f"{_MOST_REPETITIONS} repetitions find only {hit:.3f} of edited copies of items of {n} words")
            places = np.sort(np.random.default_rng([seed, n, reps]).integers(0, _WALK * n * 2 // 3, (reps, sampled)), axis=1)
            keys = walk_samples(whole, places, seed)
            own = np.tile(keys, (1, len(trials) // len(members)))
            hit = (own == walk_samples(copies, places, seed)).any(axis=0).mean()
        found.append((hit, len(trials)))
        order = np.argsort(keys, axis=None)
        index.by_length[n] = (places, keys.ravel()[order], np.tile(np.array(members), reps)[order])
    index.recall = float(sum(h * t for h, t in found) / sum(t for _, t in found))
    return index


def find_items(index: BenchmarkIndex, texts: list[str | None]) -> list[tuple[int, int, int, int, int, int]]:
    """(place of the text, item id, edits, words of the item, first word and end of the stretch), one for each text and item."""
    verbatim = _short_items(index, texts) if index.short else []
    if not index.ids:
        return verbatim
    shortest = min(index.by_length)
    span, room = shortest - 2, index.allowance
    needed = min(-(-(n - 2 - 3 * room(n)) // -(-(n + room(n) - 2) // span)) for n in index.by_length)
    shift = np.uint64(64 - (len(index.bitmap).bit_length() - 1))
    windows: dict[int, list[tuple[int, np.ndarray, np.ndarray]]] = {}
    for at, text in enumerate(texts):
        words = normal_words(text)
        if len(words) < shortest - room(shortest):
            continue
        runs = _runs(words)
        hits = index.bitmap[(runs >> shift).astype(np.int64)]
        if hits.sum() < needed:
            continue
        maybe = np.flatnonzero(hits)
        spot = np.searchsorted(index.runs, runs[maybe])
        same = index.runs[np.minimum(spot, len(index.runs) - 1)] == runs[maybe]
        hits[maybe] = same
        spot = np.unique(spot[same])
        starts, items = index.holders
        shared = np.bincount(np.concatenate([items[starts[k] : starts[k + 1]] for k in spot.tolist()] or [[]]).astype(np.int64), minlength=len(index.ids))
        lengths = set(index.lengths[shared >= index.distinct - 3 * index.rooms].tolist())
        if not lengths:
            continue
        total = np.concatenate([[0], np.cumsum(hits)])
        last = len(total) - 1
        if (total[np.minimum(np.arange(len(total)) + span, last)] - total).max() < needed:
            continue
        begins = np.arange(len(words))
        for n in lengths:
            least = n - 2 - 3 * room(n)
            fit = begins[total[np.minimum(begins + n + room(n) - 2, last)] - total[np.minimum(begins, last)] >= least]
            if len(fit):
                windows.setdefault(n, []).append((at, fit, words))
    found: dict[tuple[int, int], list[tuple[int, int, int]]] = {}
    asked: dict[tuple[int, int], list[int]] = {}
    for n, groups in windows.items():
        places, keys, owners = index.by_length[n]
        for rows, where in _blocks(groups, n):
            sample = walk_samples(rows, places, index.seed)
            left, right = np.searchsorted(keys, sample, "left"), np.searchsorted(keys, sample, "right")
            met = {(int(w), int(owners[k])) for r, w in zip(*np.nonzero(right > left), strict=True) for k in range(left[r, w], right[r, w])}
            for w, item in sorted(met):
                group, begin = where[w]
                at, _, words = groups[group]
                # What one check covers needs no other, and nothing is better than no edits. Windows of a text come in order.
                if begin - asked.get((at, item), -len(words) - n) <= room(n) // 2 or found.get((at, item), (1,))[0] == 0:
                    continue
                asked[at, item] = begin
                first = max(0, begin - 2 * room(n))
                stretch = words[first : begin + n + 2 * room(n)].tolist()
                if sum(map(set(stretch).__contains__, index.words[item])) < n - room(n):
                    continue
                edits, lo, hi = best_stretch(index.words[item], stretch)
                if edits <= room(n):
                    found[at, item] = min(found.get((at, item), (edits, first + lo, first + hi)), (edits, first + lo, first + hi))
    return verbatim + [(at, index.ids[item], hit[0], len(index.words[item]), *hit[1:]) for (at, item), hit in sorted(found.items())]


def _blocks(groups: list[tuple[int, np.ndarray, np.ndarray]], n: int) -> Iterator[tuple[np.ndarray, list[tuple[int, int]]]]:
    """Windows of n words and (place in groups, first word) of each, so many at once; a text's windows are in order."""
    rows, where, held = [], [], 0
    for g, (_, fit, words) in enumerate(groups):
        padded = np.concatenate([words, np.zeros(n, np.uint64)])
        for low in range(0, len(fit), _WINDOWS):
            part = fit[low : low + _WINDOWS]
            rows.append(padded[part[:, None] + np.arange(n)])
            where += [(g, b) for b in part.tolist()]
            held += len(part)
            if held >= _WINDOWS:
                yield np.concatenate(rows), where
                rows, where, held = [], [], 0
    if held:
        yield np.concatenate(rows), where


def _short_items(index: BenchmarkIndex, texts: list[str | None]) -> list[tuple[int, int, int, int, int, int]]:
    """As find_items, for items of few words: the first place of each in each text."""
    found = []
    for at, text in enumerate(texts):
        words = normal_words(text)
        for n, (hashes, ids) in index.short.items():
            grams, first = np.unique(_grams(words, n), return_index=True)
            low, high = np.searchsorted(hashes, grams, "left"), np.searchsorted(hashes, grams, "right")
            found += [(at, ids[k], 0, n, int(first[g]), int(first[g]) + n) for g in np.flatnonzero(high > low).tolist() for k in range(low[g], high[g])]
    return sorted(found)


def load_blocks(benchmark: DataFrame, most_bytes: int = 32 << 20, **options) -> Iterator[BenchmarkIndex]:
    """Indexes of the benchmark (item_id, text) in blocks of at most `most_bytes` of text; null texts hold nothing."""
    rows = only(benchmark, ["item_id", "text"]).where("item_id is not null and text is not null").orderBy("item_id")
    block, size = [], 0
    for r in rows.toLocalIterator():
        if block and size + len(r.text) > most_bytes:
            yield build_index(block, **options)
            block, size = [], 0
        block.append((r.item_id, r.text))
        size += len(r.text)
    if block:
        yield build_index(block, **options)


def contaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """(doc_id, item_id, edits, item_words, first_word, end_word): each benchmark item found in each document, at its best place.

    Null and empty texts hold nothing; a row without an id is reported with a null id; repeated rows are each reported; an item
    that occurs twice with the same id is reported for each of its texts. Without items, or documents, no rows.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    docs, schema, result = only(docs, ["doc_id", "text"]), f"doc_id {kind}, item_id long, edits int, item_words int, first_word long, end_word long", None
    for index in load_blocks(benchmark, **options):

        def of(batches: Iterator[pa.RecordBatch], index: BenchmarkIndex = index) -> Iterator[pa.RecordBatch]:
            for batch in slices(batches):
                found = find_items(index, batch.column(1).to_pylist())
                at, *rest = zip(*found, strict=True) if found else [()] * 6
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(pa.array(at, pa.int64())), *[pa.array(x, t) for x, t in zip(rest, (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)]],
                    names=["doc_id", "item_id", "edits", "item_words", "first_word", "end_word"],
                )

        part = docs.mapInArrow(of, schema)
        result = part if result is None else result.unionByName(part)
    return result if result is not None else docs.sparkSession.createDataFrame([], schema)


def keep_clean(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """The rows, with all their columns, in which no benchmark item is found."""
    for index in load_blocks(benchmark, **options):

        def decide(texts: list[str | None], index: BenchmarkIndex = index) -> list[bool]:
            bad = {f[0] for f in find_items(index, texts)}
            return [i not in bad for i in range(len(texts))]

        docs = keep_rows(docs, "text", decide)
    return docs
