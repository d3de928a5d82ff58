"""Toxicity by a factorization machine over hashed terms.

A text's terms are its words and their first letters (stems, so that compounds and endings count), lower-cased and
hashed. The machine's score is a bias, a weight for each term that occurs, and for each pair of terms the product of
their factors, so that two harmless terms can be toxic together. Weights are learned on a bounded sample of labelled
documents; every term that occurs in enough of them carries a weight and factors. Terms that tell by themselves learn
first, and all terms then learn together from what those leave unexplained.

Defined cases: a null or empty text has no terms and gets the bias alone; without usable labels every score is the
share of label 1, or 0; repeated rows and null ids are rows like others.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import labelled_sample, remainder, table, travels
from .textkit import LETTER, LOWER, U, Slab, distinct_by_text, hash_runs, runs, slabs

travels(__name__)

#: Labelled documents that the machine is fitted on, at most about.
TRAIN_DOCS = 12000
BITS = 20
FACTORS = 4
MIN_DOCS = 4
#: Of the terms that learn later: the size of their first factors as a share, and what their steps are divided by at first.
LATER, DAMP = 0.25, 1e-2
STEMS = (4, 5, 6)
#: Texts whose terms the fit looks at together outside its steps, so that the driver holds each term in 8 bytes.
BLOCK_DOCS = 512
THRESHOLD = 0.7


def terms(slab: Slab) -> tuple[np.ndarray, np.ndarray]:
    """The distinct term buckets of each text, and their texts."""
    buf = LOWER[slab.buf]
    s, e, t = runs(LETTER[buf], slab.off)
    hashes, owners = [hash_runs(buf, s, e)], [t]
    for k in STEMS:
        long = np.flatnonzero(e - s > k)
        hashes.append(hash_runs(buf, s[long], s[long] + k) + U(k))
        owners.append(t[long])
    h, owner = distinct_by_text(np.concatenate(hashes), np.concatenate(owners))
    bucket, owner = distinct_by_text((h >> U(54 - BITS)) << U(10), owner)
    return bucket.astype(np.int64), owner


def gather(sample: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Labels, buckets and offsets of the sampled texts, in the order of their ids."""

    def work(batches):
        for b in batches:
            for slab in slabs(b.column(0)):
                bucket, owner = terms(slab)
                cut = np.searchsorted(owner, np.arange(len(slab) + 1))
                rows = slice(slab.lo, slab.lo + len(slab))
                yield pa.RecordBatch.from_arrays(
                    [b.column(2)[rows], b.column(1)[rows], pa.array([bucket[cut[i] : cut[i + 1]].astype("<i4").tobytes() for i in range(len(slab))], pa.binary())], ["doc_id", "y", "terms"]
                )

    got = sample.select(F.col("text").cast("string"), "y", F.col("doc_id").cast("long")).mapInArrow(work, "doc_id long, y int, terms binary").toArrow()
    order = pc.sort_indices(got, [("doc_id", "ascending"), ("y", "ascending")]).to_numpy()
    sizes = pc.binary_length(got["terms"]).to_numpy().astype(np.int64)[order] // 4
    off = np.zeros(len(order) + 1, np.int64)
    np.cumsum(sizes, out=off[1:])
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    bucket, row = np.empty(off[-1], np.int32), 0
    for chunk in got["terms"].chunks:  # each row's terms go straight to their place
        for v in chunk:
            bucket[off[place[row]] : off[place[row] + 1]] = np.frombuffer(v.as_buffer(), "<i4")
            row += 1
    return got["y"].to_numpy()[order].astype(np.int64), bucket, off


class Machine:
    """``index`` maps buckets to weights; -1 where a bucket carries none."""

    def __init__(self, bias: float):
        self.bias, self.index, self.w, self.v = bias, np.full(1 << BITS, -1, np.int32), np.zeros(0), np.zeros((0, FACTORS))

    def raw(self, bucket: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
        at = self.index[bucket]
        known = at >= 0
        at, owner = at[known], owner[known]
        out = self.bias + np.bincount(owner, weights=self.w[at], minlength=n)
        for f in range(self.v.shape[1]):
            x = self.v[at, f]
            out += 0.5 * (np.bincount(owner, weights=x, minlength=n) ** 2 - np.bincount(owner, weights=x * x, minlength=n))
        return out


def blocks(bucket: np.ndarray, off: np.ndarray):
    """Some texts at a time: their first number, the buckets of their terms, and the texts of these, from 0."""
    for lo in range(0, len(off) - 1, BLOCK_DOCS):
        cut = off[lo : lo + BLOCK_DOCS + 1]
        yield lo, bucket[cut[0] : cut[-1]], np.repeat(np.arange(len(cut) - 1), np.diff(cut))


def placed(bucket: np.ndarray, off: np.ndarray, index: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
    """What ``index`` gives for the ``total`` terms that it knows, and the offsets of their texts."""
    at, cut, end = np.empty(total, np.int32), np.zeros(len(off), np.int64), 0
    for lo, b, own in blocks(bucket, off):
        here = index[b]
        known = here >= 0
        here, n = here[known], int(known.sum())
        at[end : end + n] = here
        end += n
        size = min(BLOCK_DOCS, len(off) - 1 - lo)
        cut[lo + 1 : lo + 1 + size] = np.bincount(own[known], minlength=size)
    return at, np.cumsum(cut)


def learn(y: np.ndarray, bucket: np.ndarray, off: np.ndarray, epochs: int = 12, rate: float = 0.1, decay: float = 2e-4, seed: int = 7) -> Machine:
    """Logistic loss by minibatches with adaptive steps; a few terms in all texts and rare ones are left out."""
    n = len(y)
    share = float(y.mean()) if n else 0.0
    model = Machine(float(np.log((share + 1e-9) / (1 - share + 1e-9))))
    if n == 0 or share in (0.0, 1.0):
        return model
    rng = np.random.default_rng(seed)
    df, hits = np.zeros((2, 1 << BITS), np.int64)
    for lo, b, own in blocks(bucket, off):
        df += np.bincount(b, minlength=1 << BITS)
        hits += np.bincount(b[y[lo + own] == 1], minlength=1 << BITS)
    kept = np.flatnonzero(df >= min(MIN_DOCS, max(2, n // 200)))
    # terms whose share of label 1 differs from the whole's by more than chance explains learn first, then all of them on
    # what is left unexplained: what is neutral alone may matter in a pair
    first_ = np.abs(hits - df * share)[kept] > 2.5 * np.sqrt(df[kept] * share * (1 - share) + 1e-9)
    model.index[kept] = np.arange(len(kept))
    w, v = np.zeros(len(kept)), rng.normal(0, 0.02, (len(kept), FACTORS)) * np.where(first_, 1, LATER)[:, None]
    # the others' steps begin smaller, since rare terms would else learn single texts by heart
    gw, gb, bias = np.where(first_, 1e-6, DAMP), 1e-6, model.bias
    gv = np.repeat(gw[:, None], FACTORS, 1)
    for epoch in range(2 * epochs):
        if epoch in (0, epochs):
            now, at = kept[first_] if epoch == 0 else kept, None
            index = np.full(1 << BITS, -1, np.int32)
            index[now] = model.index[now]
            at, cut = placed(bucket, off, index, int(df[now].sum()))
        order = rng.permutation(n)
        for lo in range(0, n, 256):
            docs = order[lo : lo + 256]
            sizes = cut[docs + 1] - cut[docs]
            own = np.repeat(np.arange(len(docs)), sizes)
            first = np.cumsum(sizes) - sizes
            ids = at[np.arange(sizes.sum()) + np.repeat(cut[docs] - first, sizes)]
            x = v[ids]
            total = np.stack([np.bincount(own, weights=x[:, f], minlength=len(docs)) for f in range(FACTORS)], 1)
            square = np.bincount(own, weights=(x * x).sum(1), minlength=len(docs))
            z = bias + np.bincount(own, weights=w[ids], minlength=len(docs)) + 0.5 * ((total**2).sum(1) - square)
            err = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[docs]
            uniq, back = np.unique(ids, return_inverse=True)
            dw = np.bincount(back, weights=err[own], minlength=len(uniq)) / len(docs) + decay * w[uniq]
            pair = err[own][:, None] * (total[own] - x)
            dv = np.stack([np.bincount(back, weights=pair[:, f], minlength=len(uniq)) for f in range(FACTORS)], 1) / len(docs) + 5 * decay * v[uniq]
            gw[uniq] += dw**2
            gv[uniq] += dv**2
            w[uniq] -= rate * 3 * dw / np.sqrt(gw[uniq])
            v[uniq] -= rate * 0.2 * dv / np.sqrt(gv[uniq])
            db = err.mean()
            gb += db**2
            bias -= rate * db / np.sqrt(gb)
    model.bias, model.w, model.v = float(bias), w, v
    return model


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_DOCS, modulus: int = 3, left_out: int = 1) -> Machine:
    return learn(*gather(labelled_sample(docs, labels, "toxic", modulus, left_out, rows)))


def score_batch(texts: pa.Array, model: Machine) -> np.ndarray:
    out = np.zeros(len(texts))
    for slab in slabs(texts):
        bucket, owner = terms(slab)
        z = np.clip(model.raw(bucket, owner, len(slab)), -30, 30)
        out[slab.lo : slab.lo + len(slab)] = 1 / (1 + np.exp(-z))
    return out


def score(docs: DataFrame, model: Machine) -> DataFrame:
    """doc_id and score of every row."""
    kept = docs.sparkSession.sparkContext.broadcast(model)

    def work(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(score_batch(b.column(1), kept.value))], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(work, "doc_id long, score double")


def keep_clean(docs: DataFrame, model: Machine, threshold: float = THRESHOLD) -> DataFrame:
    """The rows of ``docs`` that score under the threshold, with all their columns."""
    kept, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index("text")

    def work(batches):
        for b in batches:
            yield b.filter(pa.array(score_batch(b.column(at), kept.value) < threshold))

    return docs.mapInArrow(work, docs.schema)


def op2_factorization_machine(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", (remainder("doc_id", 3) == 1).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
