"""Toxicity by a factorization machine over hashed terms.

The score of a text is the sigmoid of a bias, a weight for each of its distinct
terms, and the inner product of the factors of each pair of them, so that two
terms (an insult and a mention of a group) can say together what neither says
alone. Terms are lower-cased words and their openings of five characters.

The machine is fitted on the driver to a bounded sample of labelled texts
(``MOST_SAMPLED``, the rows first in the order of a hash), by minibatches with
per-coordinate steps. Rare terms are learned only where they are more or less
common among toxic texts than chance explains, among all texts or beside terms
of that kind; frequent ones whatever they say alone. Weights that the data do
not support are drawn to zero, so the many neutral words of a long text add
nothing.

Null and empty texts score like a text without known terms; a text counts whole,
however long, each term once. Labels, language, source and id never enter a score,
nor do other columns, whatever their names. Repeated rows are scored each, with
equal scores. Labels that repeat an id or contradict each other are rows of the
fit each; null labels are none. Without labels of both kinds the score is the
share of toxic labels (or 0). An empty table gives no rows.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Kept, held_by, only

TERM_BITS = 20
OPENING = 5
FACTORS = 4
MOST_SAMPLED = 12_000
#: Texts that a term must occur in to be learned.
LEAST_TEXTS = 4
THRESHOLD = 0.3
DRAW = 0.03
#: Standard deviations by which a term's share of toxic texts departs from that
#: of all texts, for it to be learned.
LEAST_APART = 3.5
#: Share of the texts from which on a term is learned whatever it says alone.
FREQUENT = 0.005
HELD_OUT = 2
_WORD = re.compile(r"\w+")
_MASK = (1 << TERM_BITS) - 1


def _term_hashes(word: str) -> tuple[int, int]:
    low = word.lower()
    return zlib.crc32(low.encode("utf-8", "surrogatepass")) & _MASK, zlib.crc32(b"^" + low[:OPENING].encode("utf-8", "surrogatepass")) & _MASK


_kept = Kept(_term_hashes, 100_000)
held_by("toxicity", _kept.empty)


def terms(text: str | None) -> np.ndarray:
    """Sorted distinct term hashes of a text."""
    if not text:
        return np.empty(0, np.int64)
    words = set(_WORD.findall(text))
    if not words:
        return np.empty(0, np.int64)
    return np.unique(np.array(list(map(_kept.__getitem__, words)), np.int64))


@dataclass
class Machine:
    """Weights of the learned terms (their hashes, ascending): linear (w) and
    pairwise (v, a row a term)."""

    bias: float
    learned: np.ndarray
    w: np.ndarray
    v: np.ndarray

    def __post_init__(self):
        self.place = np.full(1 << TERM_BITS, -1, np.int32)
        self.place[self.learned] = np.arange(len(self.learned), dtype=np.int32)

    def score(self, found: list[np.ndarray]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(found), -30, 30)))

    def margin(self, found: list[np.ndarray]) -> np.ndarray:
        out = np.full(len(found), self.bias)
        sizes = np.array([len(f) for f in found])
        if not sizes.sum() or not len(self.learned):
            return out
        at, who = self.place[np.concatenate(found)], np.repeat(np.arange(len(found)), sizes)
        some = at >= 0
        at, who = at[some], who[some]
        out += np.bincount(who, self.w[at], len(found))
        for f in range(self.v.shape[1]):
            v = self.v[at, f].astype(np.float64)
            out += 0.5 * (np.bincount(who, v, len(found)) ** 2 - np.bincount(who, v * v, len(found)))
        return out


def _occurrences(found: list[np.ndarray], which: np.ndarray) -> np.ndarray:
    """In how many of the texts that ``which`` lists each term occurs."""
    out = np.zeros(1 << TERM_BITS, np.int32)
    for lo in range(0, len(which), 1_000):
        out += np.bincount(np.concatenate([found[i] for i in which[lo : lo + 1_000]]), minlength=len(out)).astype(np.int32)
    return out


def _departs(spread: np.ndarray, among: np.ndarray, share: float) -> np.ndarray:
    """Standard deviations by which terms in ``spread`` texts, ``among`` of them
    toxic, depart from the share of toxic texts."""
    return np.abs(among - spread * share) / np.sqrt(np.maximum(spread, 1) * max(share * (1 - share), 1e-12))


def learned_terms(found: list[np.ndarray], toxic: np.ndarray, least_apart: float = LEAST_APART, frequent: float = FREQUENT) -> np.ndarray:
    """Terms that get weights, of those in ``LEAST_TEXTS`` texts: terms more or less
    common among toxic texts than chance explains, whether among all texts or among
    those that hold (or lack) a term of that kind; and, whatever their share of toxic
    texts, all terms of at least ``frequent`` of the texts, as two terms that say
    nothing each may say something together."""
    said = toxic > 0

    def departing(which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        spread = _occurrences(found, which)
        return spread, (spread >= LEAST_TEXTS) & (_departs(spread, _occurrences(found, which[said[which]]), float(said[which].mean())) >= least_apart)

    spread, apart = departing(np.arange(len(found)))
    keep = apart | (spread >= max(LEAST_TEXTS, frequent * len(found)))
    marked = np.array([bool(apart[f].any()) for f in found])
    for side in (marked, ~marked):
        if side.any():
            keep |= departing(np.flatnonzero(side))[1]
    return np.flatnonzero(keep)


def fit(found: list[np.ndarray], toxic: np.ndarray, epochs: int = 6, batch: int = 128, step: float = 0.3, draw: float = DRAW, least_steps: int = 400, least_apart: float = LEAST_APART, frequent: float = FREQUENT, seed: int = 5) -> Machine:
    """A machine for texts given by their terms. ``draw`` over the
    root of their number pulls weights to zero, as soft thresholds; few texts
    are gone through more often."""
    toxic = toxic.astype(np.float64)
    share = float(toxic.mean()) if len(toxic) else 0.0
    if not 0 < share < 1:
        return Machine(30.0 if share == 1 else -30.0, np.empty(0, np.int64), np.empty(0, np.float32), np.empty((0, FACTORS), np.float32))
    kept_terms = learned_terms(found, toxic, least_apart, frequent)
    place = np.full(1 << TERM_BITS, -1)
    place[kept_terms] = np.arange(len(kept_terms))
    own = [at[at >= 0].astype(np.int32) for at in (place[f] for f in found)]
    draw /= len(found) ** 0.5
    epochs = max(epochs, -(-least_steps * batch // len(found)))
    rng = np.random.default_rng(seed)
    w, gw = np.zeros(len(kept_terms)), np.full(len(kept_terms), 1e-3)
    v, gv = rng.normal(0, 0.01, (len(kept_terms), FACTORS)), np.full((len(kept_terms), FACTORS), 1e-2)
    bias = float(np.log(share / (1 - share)))
    for _ in range(epochs):
        order = rng.permutation(len(own))
        for lo in range(0, len(order), batch):
            rows = [own[i] for i in order[lo : lo + batch]]
            y = toxic[order[lo : lo + batch]]
            n = np.array([len(r) for r in rows])
            if not n.sum():
                continue
            flat, who = np.concatenate(rows), np.repeat(np.arange(len(rows)), n)
            vf = v[flat]
            s = np.zeros((len(rows), FACTORS))
            for f in range(FACTORS):
                s[:, f] = np.bincount(who, vf[:, f], len(rows))
            q = np.bincount(who, (vf * vf).sum(axis=1), len(rows))
            m = bias + np.bincount(who, w[flat], len(rows)) + 0.5 * ((s * s).sum(axis=1) - q)
            err = (1 / (1 + np.exp(-np.clip(m, -30, 30))) - y) / len(rows)
            bias -= 0.05 * err.sum() * len(rows) / batch
            e = err[who]
            used, back = np.unique(flat, return_inverse=True)
            g = np.bincount(back, e, len(used))
            gw[used] += g * g
            pace = step / np.sqrt(gw[used])
            new = w[used] - pace * g
            w[used] = np.sign(new) * np.maximum(np.abs(new) - pace * draw, 0)
            for f in range(FACTORS):
                gf = np.bincount(back, e * (s[who, f] - vf[:, f]), len(used))
                gv[used, f] += gf * gf
                pace = 0.1 * step / np.sqrt(gv[used, f])
                new = v[used, f] - pace * gf
                v[used, f] = np.sign(new) * np.maximum(np.abs(new) - pace * draw, 0)
    return Machine(bias, kept_terms, w.astype(np.float32), v.astype(np.float32))


def remainder(doc_id="doc_id"):
    """crc32(doc_id as text) mod 4; null ids count as empty."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % 4


def train(docs: DataFrame, labels: DataFrame, most: int = MOST_SAMPLED, exclude: int | None = HELD_OUT) -> Machine:
    """Fits on at most ``most`` labelled rows outside the held-out remainder."""
    known = labels.where("toxic is not null").select(F.col("doc_id").alias("_id"), "toxic")
    if exclude is not None:
        known = known.where(remainder("_id") != exclude)
    known = known.withColumn("_h", F.md5(F.concat(F.lit("fit-"), F.col("_id").cast("string")))).orderBy("_h", "_id", "toxic").limit(most).select("_id", "toxic")
    known = F.broadcast(known)  # ``most`` rows at the most
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(known, F.col("doc_id") == F.col("_id")).select("doc_id", "text", "toxic")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([terms(t).astype(np.int32).tobytes() for t in b.column(1).to_pylist()], pa.binary()), b.column(2)], names=["doc_id", "terms", "toxic"])

    kinds = dict(rows.dtypes)
    got = rows.mapInArrow(run, f"doc_id {kinds['doc_id']}, terms binary, toxic {kinds['toxic']}").toArrow()
    listed = sorted(zip(got["doc_id"].to_pylist(), got["toxic"].to_pylist(), got["terms"].to_pylist()))
    del got
    machine = fit([np.frombuffer(t, np.int32) for _, _, t in listed], np.array([y for _, y, _ in listed], np.float64))
    pa.default_memory_pool().release_unused()
    return machine


def _scorer(machine: Machine):
    """What scores lists of texts in a worker: only learned terms are sent (a bound of
    2 ** TERM_BITS, in truth some thousands)."""
    parts = (machine.bias, machine.learned, machine.w, machine.v)

    def make():
        only("toxicity")
        use = Machine(*parts)
        return lambda texts: use.score([terms(t) for t in texts])

    return make


def score_documents(docs: DataFrame, machine: Machine, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, score and predicted of every whole text."""
    make = _scorer(machine)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = make()
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                b = whole.slice(lo, 256)
                found = score(b.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(found, pa.float64()), pa.array((found >= threshold).astype(np.int32))], names=["doc_id", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, score double, predicted int")


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted of every row of ``docs``."""
    return score_documents(docs, train(docs, labels)).select("doc_id", (remainder() == HELD_OUT).alias("held_out"), "score", "predicted")


def clean_documents(docs: DataFrame, labelled: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are not predicted toxic, by a machine fitted to
    the labelled rows of ``labelled``. The texts pass through, without a join."""
    make = _scorer(train(labelled, labels))
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = make()
        for whole in batches:
            for lo in range(0, whole.num_rows, 256):
                b = whole.slice(lo, 256)
                yield b.filter(pa.array(score(b.column(at).to_pylist()) < THRESHOLD))

    return docs.mapInArrow(run, docs.schema)
