"""Tokens, sentences, hashed word vectors and distances as Columns.

Vectors are integer counts by bucket, so dot products and norms are exact in any order and in any engine.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections import Counter
from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

DIMENSIONS = 256
#: Very common short words of the four languages of the corpus.
STOP_WORDS = "a an and are as at by de der die das des du el en et for from in is it la las le les los of on or the to un und une with y zu".split()
#: Separators of space, of Unicode's category Zs: what `trim` takes off in SQL.
_BLANKS = " \u00a0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u202f\u205f\u3000"
_EDGES = r"^[^\p{L}\p{N}#]+|[^\p{L}\p{N}#]+$"


def n_tokens(text: Column) -> Column:
    """Runs of characters other than white space: the unit of cost."""
    return F.coalesce(F.size(F.regexp_extract_all(text, F.lit(r"\S+"), 0)), F.lit(0))


def sentences(text: Column) -> Column:
    """Sentences of a text, in order: cut at line feeds and after . ! ? before white space."""
    cut = F.split(F.regexp_replace(text, r"([.!?])\s+", "$1\n"), r"\n+")
    return F.filter(F.transform(cut, lambda s: F.trim(s, F.lit(_BLANKS))), lambda s: s != "")


def words(text: Column) -> Column:
    """Lowered words without punctuation at their edges, digits as #, stop words left out."""
    raw = F.transform(F.regexp_extract_all(F.lower(text), F.lit(r"\S+"), 0), lambda w: F.regexp_replace(F.regexp_replace(w, r"[0-9]+", "#"), _EDGES, ""))
    return F.filter(raw, lambda w: (w != "") & ~w.isin(STOP_WORDS))


def bucket(word: Column, d: int = DIMENSIONS) -> Column:
    return (F.conv(F.substring(F.md5(word), 1, 7), 16, 10).cast("bigint") % d).cast("int")


def embed(text: Column, d: int = DIMENSIONS) -> Column:
    """map<int,int>: how many words of the text fall into each bucket."""
    count = lambda bs: F.map_from_entries(F.transform(F.array_distinct(bs), lambda x: F.struct(x, F.size(F.filter(bs, lambda y: y == x)))))
    hashed = F.array_sort(F.transform(words(text), lambda w: bucket(w, d)))
    return F.element_at(F.transform(F.array(hashed), count), 1)


def norm2(vector: Column) -> Column:
    return F.aggregate(F.map_values(vector), F.lit(0).cast("bigint"), lambda s, x: s + x.cast("bigint") * x)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.map_entries(a), F.lit(0).cast("bigint"), lambda s, e: s + e["value"].cast("bigint") * F.coalesce(F.try_element_at(b, e["key"]), F.lit(0)))


def distance(a: Column, b: Column, a2: Column, b2: Column) -> Column:
    """Euclidean distance of the normalised vectors, from their dot product and squared norms; an empty vector is at distance sqrt 2."""
    cos = F.when((a2 > 0) & (b2 > 0), dot(a, b) / F.sqrt(a2.cast("double") * b2.cast("double"))).otherwise(0.0)
    return F.sqrt(F.greatest(F.lit(0.0), 2 - 2 * cos))


def distance_to(vector: Column, squared: Column, centre: Sequence[float]) -> Column:
    """Distance of the normalised vector from a fixed point of doubles, a constant of the plan."""
    at = F.lit([float(x) for x in centre])
    inner = F.aggregate(F.map_entries(vector), F.lit(0.0), lambda s, e: s + e["value"] * F.element_at(at, e["key"] + 1))
    unit = F.when(squared > 0, inner / F.sqrt(squared.cast("double"))).otherwise(0.0)
    own = F.when(squared > 0, 1.0).otherwise(0.0)
    return F.sqrt(F.greatest(F.lit(0.0), own + float(sum(x * x for x in centre)) - 2 * unit))


def l2n(vector: Column) -> Column:
    """An array of doubles scaled to length one; the zero vector stays."""
    length = F.sqrt(F.aggregate(vector, F.lit(0.0), lambda s, x: s + x * x))
    return F.transform(vector, lambda x: F.when(length > 0, x / length).otherwise(0.0))


def dense_dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def euclid(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x.cast("double") - y) * (x.cast("double") - y)), F.lit(0.0), lambda s, x: s + x))


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dense_dot(a, b), F.sqrt(dense_dot(a, a) * dense_dot(b, b)))


def python_words(text: str) -> list[str]:
    found = [re.sub(r"^[^\w#]+|[^\w#]+$|^_+|_+$", "", re.sub(r"[0-9]+", "#", w)) for w in text.lower().split()]
    return [w for w in found if w and w not in STOP_WORDS]


def python_embed(text: str, d: int = DIMENSIONS) -> dict[int, int]:
    """The same counts for short texts on the driver: attribute names and descriptions."""
    return dict(Counter(int(hashlib.md5(w.encode()).hexdigest()[:7], 16) % d for w in python_words(text)))


def unit(counts: dict[int, int], d: int = DIMENSIONS) -> list[float]:
    length = math.sqrt(sum(c * c for c in counts.values())) or 1.0
    return [counts.get(i, 0) / length for i in range(d)]


def md5_rank(key: Column, seed: str) -> Column:
    """A reproducible draw in [0, 1) of a key, the same in any engine."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}:"), key.cast("string"))), 1, 12), 16, 10).cast("double") / float(16**12)
