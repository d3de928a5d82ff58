"""Language identification by mixture inference.

Each language has a model of hashed byte n-grams inside words. A text is cut into units of a few words; expectation-
maximisation estimates what share of the units each language wrote, and languages leave the set one by one, least
share first, as long as the likelihood penalised by the number of languages gets no worse. The models count every
training text of a language, so that a rare one is learned from all that it has.

Defined cases: a null text, or one without a letter, is ``und`` with score 0; without any learned language every text
is ``und``; ties go to the language first in code-point order; null ids and repeated rows are rows like others.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import remainder, table, travels
from .textkit import LETTER, LOWER, Slab, runs, slabs

travels(__name__)

BITS = 16
#: Groups of tasks whose counts are added up before those of a whole language.
SLOTS = 64
UNIT_WORDS = 4
ROUNDS = 8
#: How much of a unit's log-likelihood counts: its n-grams overlap, so they tell less than as many separate ones.
WEIGHT = 0.25
ALPHA = 0.5
SET = pa.list_(pa.struct([("lang", pa.string()), ("share", pa.float64())]))


def grams(slab: Slab) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Buckets of the four-byte windows that end after each letter, the first window of each word, words' texts, ends."""
    b = LOWER[slab.buf]
    ws, we, wt = runs(LETTER[b], slab.off)
    if not len(ws):
        e = np.zeros(0, np.int64)
        return e, e, wt, e
    size = we - ws
    first = np.cumsum(size) - size
    at = np.arange(size.sum()) + np.repeat(ws - first, size)
    left = at - np.repeat(ws, size)
    right = np.repeat(we, size) - at
    x = b[at].astype(np.int64)
    n = len(b) - 1
    one = np.where(left > 0, b[np.maximum(at - 1, 0)], 0).astype(np.int64)
    two = np.where(left > 1, b[np.maximum(at - 2, 0)], 0).astype(np.int64)
    nxt = np.where(right > 1, b[np.minimum(at + 1, n)], 0).astype(np.int64)
    code = ((two << 24) | (one << 16) | (x << 8) | nxt) * 0x9E3779B1 & 0xFFFFFFFF
    return code >> (32 - BITS), first, wt, we


def learn(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """Languages in code-point order and the log-probability of each bucket in each; ``docs`` has lang and text."""
    named = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull())

    def rows(found, slot):
        for name, c in found.items():
            yield pa.RecordBatch.from_arrays([pa.array([slot], pa.int32()), pa.array([name]), pa.array([zlib.compress(c.astype("<i8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1)], pa.binary())], ["slot", "lang", "counts"])

    def count(batches):
        found: dict[str, np.ndarray] = {}
        for b in batches:
            lang = b.column(0).dictionary_encode()
            order = np.argsort(lang.indices.to_numpy(), kind="stable")  # so that few languages share a slab
            code, texts = lang.indices.to_numpy()[order], b.column(1).take(pa.array(order))
            for slab in slabs(texts):
                bucket, first, wt, _ = grams(slab)
                mine = code[slab.lo + np.repeat(wt, np.diff(np.r_[first, len(bucket)]))]
                for k in np.unique(mine).tolist():
                    name = lang.dictionary[k].as_py()
                    found[name] = found.get(name, 0) + np.bincount(bucket[mine == k], minlength=1 << BITS)
        yield from rows(found, TaskContext.get().partitionId() % SLOTS)

    def add_up(batches):
        found: dict[str, np.ndarray] = {}
        for b in batches:
            for name, c in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                found[name] = found.get(name, 0) + np.frombuffer(zlib.decompress(c), np.uint8).reshape(8, -1).T.copy().view("<i8").ravel()
        yield from rows(found, 0)

    schema = "slot int, lang string, counts binary"
    parts = named.select("lang", F.col("text").cast("string")).mapInArrow(count, schema)
    parts = parts.repartition(SLOTS, "slot", "lang").mapInArrow(add_up, schema).repartition(8, "lang").mapInArrow(add_up, schema)
    got = {r["lang"]: np.frombuffer(zlib.decompress(r["counts"]), np.uint8).reshape(8, -1).T.copy().view("<i8").ravel() for r in parts.collect()}  # one row a language
    names = sorted(got)
    table_ = np.zeros((1 << BITS, len(names)), np.float32)
    for k, name in enumerate(names):
        table_[:, k] = np.log((got[name] + ALPHA) / (got[name].sum() + ALPHA * (1 << BITS)))
    return names, table_


def mixture(like: np.ndarray, first: np.ndarray, size: np.ndarray, active: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """Shares of the active languages and log-likelihood of each text; ``like`` are the units' likelihoods, scaled."""
    pi = active / active.sum(1, keepdims=True)
    owner = np.repeat(np.arange(len(first)), size)
    for _ in range(rounds):
        r = like * pi[owner]
        r /= np.maximum(r.sum(1, keepdims=True), 1e-300)
        pi = np.add.reduceat(r, first, axis=0) / size[:, None]
    total = np.log(np.maximum((like * pi[owner]).sum(1), 1e-300))
    return pi, np.add.reduceat(total, first)


def infer(slab: Slab, logp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The likeliest language of each text (-1 where it has no word), its share, and the shares of all languages, 0
    for those outside the chosen set."""
    m, k = len(slab), logp.shape[1]
    best, share, every = np.full(m, -1), np.zeros(m), np.zeros((m, k))
    bucket, first, wt, _ = grams(slab)
    if not len(wt) or not k:
        return best, share, every
    words = np.add.reduceat(logp[bucket], first, axis=0).astype(np.float64)
    new = np.r_[True, wt[1:] != wt[:-1]]
    start = np.flatnonzero(new)
    rank = np.arange(len(wt)) - np.repeat(start, np.diff(np.r_[start, len(wt)]))
    unit = np.flatnonzero(rank % UNIT_WORDS == 0)
    score = np.add.reduceat(words, unit, axis=0) * WEIGHT
    like = np.exp(score - score.max(1, keepdims=True))
    text = wt[unit]
    head = np.flatnonzero(np.r_[True, text[1:] != text[:-1]])
    size = np.diff(np.r_[head, len(text)])
    active = np.ones((len(head), k))
    pi, ll = mixture(like, head, size, active, ROUNDS)
    cost = 0.5 * np.log(np.maximum(size, 2))
    open_ = np.ones(len(head), bool)
    for _ in range(k - 1):
        weakest = np.where(active > 0, pi, np.inf).argmin(1)
        trial = active.copy()
        rows = np.flatnonzero(open_)
        if not len(rows):
            break
        trial[rows, weakest[rows]] = 0
        pi2, ll2 = mixture(like, head, size, trial, ROUNDS // 2)
        better = open_ & (ll2 + cost >= ll)
        active[better], pi[better], ll[better] = trial[better], pi2[better], ll2[better]
        open_ = better
    best[text[head]] = pi.argmax(1)
    share[text[head]] = np.clip(pi.max(1), 0, 1)
    every[text[head]] = pi
    return best, share, every


def identify(docs: DataFrame, names: list[str], logp: np.ndarray) -> DataFrame:
    """doc_id, lang_pred, score, and languages: the chosen set with each one's share, largest first, of every row."""
    kept = docs.sparkSession.sparkContext.broadcast(logp)

    def work(batches):
        for b in batches:
            texts = b.column(1)
            best, share, every = np.full(b.num_rows, -1), np.zeros(b.num_rows), np.zeros((b.num_rows, len(names)))
            for slab in slabs(texts):
                here = slice(slab.lo, slab.lo + len(slab))
                best[here], share[here], every[here] = infer(slab, kept.value)
                ascii_ = np.r_[0, np.cumsum(LETTER[slab.buf] & (slab.buf < 128))]
                for i in np.flatnonzero((ascii_[slab.off[1:]] == ascii_[slab.off[:-1]]) & (best[here] >= 0)).tolist():
                    if not any(c.isalpha() for c in texts[slab.lo + i].as_py()):
                        best[slab.lo + i] = -1
            share[best < 0] = 0.0
            every[best < 0] = 0.0
            order = np.argsort(-every, axis=1, kind="stable")
            sets = [[{"lang": names[k], "share": float(x[k])} for k in o if x[k] > 0] for x, o in zip(every, order.tolist(), strict=True)]
            pred = [names[i] if i >= 0 else "und" for i in best.tolist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(pred, pa.string()), pa.array(share), pa.array(sets, SET)], ["doc_id", "lang_pred", "score", "languages"])

    schema = "doc_id long, lang_pred string, score double, languages array<struct<lang:string,share:double>>"
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(work, schema)


def op8_mixture_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    names, logp = learn(docs.where(remainder("doc_id", 4) != 2))
    return identify(docs, names, logp).select("doc_id", (remainder("doc_id", 4) == 2).alias("held_out"), "lang_pred", "score", "languages")
