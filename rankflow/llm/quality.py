"""Quality by importance resampling.

Two generative models over hashed n-grams are counted: one of the target (texts
labelled good, a bounded number of them) and one of all raw texts. A document's importance is the log of
the ratio of its probabilities under them. Documents are drawn without
replacement by Gumbel top-k: the k largest of importance plus Gumbel noise.

Features are words, marks (runs of signs) and pairs of neighbours.
A pair of equal neighbours is one feature whatever its word, and the case of a
word and long signs have features of their own, so that texts the words of
which are new can still be told apart by how they are built.

The sum over a text's features grows with its length, so documents are drawn by
their importance a feature, as if all had ``LENGTH`` features; a few more that say
nothing (``PSEUDO``) keep very short texts near zero. k is a parameter: a number
of documents, a share of them, or, if not given, the number of those above the
level that parts labelled good texts from labelled bad ones best (0, as likely
under either model, without both kinds). That level does not move with the sizes
of texts or samples.

Null and empty texts have no features and importance 0; texts count whole, however
long. The noise is a hash of doc_id, so reruns agree; ties rank by doc_id. Rows
that repeat an id are scored each and share their noise. Without good labels all
importances are 0. An empty table gives no rows. Other columns are never looked
at, whatever their names.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pandas.util import hash_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_names, global_rank, only, staged

#: Hashed features of each kind: 0 words and marks, 1 pairs, 2 forms.
BUCKETS = 8_192
KINDS = 3
#: The target model starts as so many tokens of the raw model, so a feature without
#: evidence says nothing.
PRIOR, FLOOR = 1_000.0, 0.01
#: Labelled good texts that the target model counts at most; the raw model counts
#: all texts.
MOST_GOOD = 20_000
#: Features of the text that an importance a feature is scaled to, and those that are
#: added to each text's own.
LENGTH, PSEUDO = 200.0, 20.0
SEED = 7
#: Texts, and characters of texts, that are unpacked together.
TOGETHER, TOGETHER_CHARS = 2_048, 1 << 21
_TOKEN = re.compile(r"\x00|\w+|[^\w\s\x00]+")
_MIX = np.uint64(0x9E3779B97F4A7C15)


def _hashes(tokens: pa.StringArray) -> np.ndarray:
    """Hashes of different tokens, lower-cased; the low bits are the bucket of the
    form: kind of word and length, or sign and length."""

    def plain(x: pa.Array) -> np.ndarray:
        return x.to_numpy(zero_copy_only=False)

    first, n = pc.utf8_slice_codeunits(tokens, 0, 1), plain(pc.utf8_length(tokens)).astype(np.int64)
    word = plain(pc.or_(pc.utf8_is_alnum(first), pc.equal(first, "_")))
    upper, title, digit = plain(pc.utf8_is_upper(tokens)) & (n > 1), plain(pc.utf8_is_upper(first)), plain(pc.utf8_is_digit(first))
    kind = np.select([upper, title, digit], [0, 1, 2], 3)
    signs = first.dictionary_encode()
    sign = hash_array(plain(signs.dictionary), categorize=False)[plain(signs.indices)] % np.uint64(BUCKETS // 4)
    form = np.where(word, kind * 5 + np.minimum(n, 24) // 6, 32 + 3 * sign.astype(np.int64) + np.minimum(n, 3)) % BUCKETS
    h = hash_array(plain(pc.utf8_lower(tokens)), categorize=False)
    return h & ~np.uint64(BUCKETS - 1) | form.astype(np.uint64)


def _tokenised(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(which, hashes, pair, marks): the place of each token of ``texts`` among
    the different ones, their hashes, the bucket of the pair that each token begins, and where marks are."""
    joined = "\0".join([t.replace("\0", " ") if "\0" in t else t for t in texts])
    found = pa.array(_TOKEN.findall(joined), pa.string()).dictionary_encode()
    which = found.indices.to_numpy()
    h = _hashes(found.dictionary) if len(which) else np.empty(0, np.uint64)
    mark = found.dictionary.index("\0").as_py()
    marks = np.flatnonzero(which == mark)
    size = np.uint64(BUCKETS)
    form, one = h % size, h // size
    left = (form * _MIX) ^ (one % np.uint64(64))
    right = form ^ (one * _MIX >> np.uint64(58) << np.uint64(20))
    p = left[which[:-1]] ^ right[which[1:]]
    p *= _MIX
    p >>= np.uint64(24)
    p %= size - np.uint64(1)
    pair = p.astype(np.int64)
    pair += 1 + BUCKETS
    pair[which[:-1] == which[1:]] = BUCKETS
    pair[marks[marks < len(pair)]] = BUCKETS * KINDS
    pair[marks[marks > 0] - 1] = BUCKETS * KINDS
    return which, h, pair, marks


def _groups(texts: list[str | None]) -> Iterator[list[str]]:
    """Runs of texts that are unpacked together."""
    group, n = [], 0
    for t in texts:
        group.append(t or "")
        n += len(group[-1])
        if n >= TOGETHER_CHARS:
            yield group
            group, n = [], 0
    if group:
        yield group


def _own(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of word and form of different tokens."""
    size = np.uint64(BUCKETS)
    return (h // size % size).astype(np.int64), (h % size).astype(np.int64) + 2 * BUCKETS


def counted(texts: list[str]) -> np.ndarray:
    """How often each feature occurs in ``texts``."""
    which, h, pair, marks = _tokenised(texts)
    n = np.bincount(which, minlength=len(h))
    if len(marks):
        n[which[marks[0]]] = 0
    words, forms = _own(h)
    out = np.bincount(pair, minlength=BUCKETS * KINDS + 1)[:-1]
    for own in (words, forms):
        np.add.at(out, own, n)
    return out


def weighed(texts: list[str], weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of features, sum of their weights) of each text. Weights are summed
    as whole numbers of 2 ** -20, so that a sum does not depend on its neighbours."""
    which, h, pair, marks = _tokenised(texts)
    w = np.append(np.round(weights * (1 << 20)).astype(np.int64), 0)
    words, forms = _own(h)
    single = w[words] + w[forms]
    if len(marks):
        single[which[marks[0]]] = 0
    each = single[which]
    each[: len(pair)] += w[pair]
    start = np.concatenate([[0], marks + 1])
    n = np.concatenate([marks, [len(each)]]) - start
    out = np.zeros(len(texts))
    some = n > 0
    if some.any():
        # a sum runs up to the next start, so over the mark, which weighs nothing
        out[some] = np.add.reduceat(each, start[some]) / (1 << 20)
    return np.maximum(3 * n - 1, 0), out


def feature_counts(docs: DataFrame) -> np.ndarray:
    """How often each feature occurs in all of ``docs``. Each task sends its sums
    once; the result has a fixed size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("quality")
        total = np.zeros(BUCKETS * KINDS, np.int64)
        for whole in batches:
            for lo in range(0, whole.num_rows, TOGETHER):
                for group in _groups(whole.column(0).slice(lo, TOGETHER).to_pylist()):
                    total += counted(group)
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], names=["bucket", "n"])

    sums = docs.select(F.col("text").cast("string")).mapInArrow(run, "bucket long, n long").groupBy("bucket").agg(F.sum("n").alias("n"))
    out = np.zeros(BUCKETS * KINDS, np.int64)
    for bucket, n in sums.collect():  # at most BUCKETS * KINDS rows
        out[bucket] = n
    return out


def log_ratios(target: np.ndarray, raw: np.ndarray) -> np.ndarray:
    """Log of the two models' ratio, by feature, each kind a model of its own."""
    out = np.zeros(BUCKETS * KINDS)
    if not target.sum():
        return out
    for k in range(KINDS):
        at = slice(k * BUCKETS, (k + 1) * BUCKETS)
        q = (raw[at] + FLOOR) / (raw[at].sum() + FLOOR * BUCKETS)
        p = (target[at] + PRIOR * q) / (target[at].sum() + PRIOR)
        out[at] = np.log(p / q)
    return out


def gumbel(key: Column, seed: int = SEED) -> Column:
    """Gumbel noise from a hash of ``key``."""
    u = (F.shiftrightunsigned(F.xxhash64(key.cast("string"), F.lit(seed)), 11) + F.lit(0.5)) / F.lit(float(1 << 53))
    return -F.log(-F.log(u))


def _first(labels: DataFrame, quality: int, most: int) -> DataFrame:
    """Ids (id_) of at most ``most`` texts labelled so, the first by a hash."""
    some = labels.where(F.col("quality") == quality).select(F.col("doc_id").alias("id_")).dropna().distinct()
    return some.orderBy(F.md5(F.concat(F.lit("good-"), F.col("id_").cast("string"))), "id_").limit(most)


def importance(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, n_features, importance (the log of the models' ratio, over all of a
    text) and rate (a feature) of every row of ``docs``."""
    texts = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    good = F.broadcast(_first(labels, 1, MOST_GOOD))  # MOST_GOOD rows at the most
    target = feature_counts(texts.join(good, F.col("doc_id") == F.col("id_"), "left_semi"))
    weights = log_ratios(target, feature_counts(texts))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        only("quality")
        for whole in batches:
            for lo in range(0, whole.num_rows, TOGETHER):
                b = whole.slice(lo, TOGETHER)
                made = [weighed(g, weights) for g in _groups(b.column(1).to_pylist())]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(np.concatenate([m[0] for m in made]), pa.int64()), pa.array(np.concatenate([m[1] for m in made]), pa.float64())], names=["doc_id", "n_features", "importance"])

    return texts.mapInArrow(run, "doc_id long, n_features long, importance double").withColumn("rate", F.col("importance") / (F.col("n_features") + PSEUDO))


def best_level(good: np.ndarray, bad: np.ndarray) -> float:
    """The middle of the levels that part good rates (above) from bad ones best, by
    the sum of both shares; 0 if there is none of a kind."""
    if not len(good) or not len(bad):
        return 0.0
    at = np.unique(np.concatenate([good, bad]))
    right = np.searchsorted(np.sort(bad), at) * len(good) - np.searchsorted(np.sort(good), at) * len(bad)  # whole numbers: equal levels tie
    best = int(right.argmax())  # a level between the value at ``best`` and the one below it
    return float(at[best] if best == 0 else (at[best] + at[best - 1]) / 2)


def _level(scored: DataFrame, labels: DataFrame) -> float:
    """``best_level`` of at most MOST_GOOD labelled rows of each kind."""
    known = [F.broadcast(_first(labels, q, MOST_GOOD)) for q in (1, 0)]
    good, bad = (np.array([r[0] for r in scored.join(k, F.col("doc_id") == F.col("id_"), "left_semi").select("rate").limit(MOST_GOOD).collect()]) for k in known)
    return best_level(good, bad)


def resample(docs: DataFrame, labels: DataFrame, k: int | float | None = None, seed: int = SEED) -> DataFrame:
    """doc_id, n_features, importance, rate, key (LENGTH times the rate, with noise),
    place (0-based by key, descending) and kept (place below k) of every row of
    ``docs``. k: a number of rows (int), a share of them (float), or None."""
    scored = staged(importance(docs, labels), "importances")
    if k is None:
        k = scored.where(F.col("rate") >= _level(scored, labels)).count()
    elif isinstance(k, float):
        k = round(k * scored.count())
    keyed = scored.withColumn("key", F.col("rate") * LENGTH + gumbel(F.col("doc_id"), seed))
    return global_rank(keyed, [F.desc("key"), F.asc("doc_id")], "place", "places").withColumn("kept", F.col("place") < k)


def good_documents(docs: DataFrame, labels: DataFrame, k: int | float | None = None) -> DataFrame:
    """The rows of ``docs`` that the draw keeps; rows that repeat a doc_id stay
    if any of them is kept, rows without one always do."""
    (own,) = free_names(docs, "gone_")
    drawn = resample(docs, labels, k)
    gone = staged(drawn.groupBy("doc_id").agg(F.max("kept").alias("kept")).where("not kept and doc_id is not null").select(F.col("doc_id").alias(own)), "rejected")
    return docs.join(gone, docs["doc_id"] == F.col(own), "left_anti")
