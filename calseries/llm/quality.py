"""Quality classifier: random-indexing word vectors, pooled per document, and a two-layer network.

A text is a sequence of tokens: runs of letters and runs of other marks, and after a word the signs that hold of it
(in capitals, said before in the text, its length), which are tokens like others. Every token bucket has a sparse
random index vector; a token's vector adds up the index vectors of its neighbours in all training texts, labelled or
not, to its own. A text is the mean of its tokens' vectors. The network has one hidden layer; a temperature fitted on
rows it wasn't trained on calibrates its probabilities.

Defined cases: a null or empty text has the zero vector and gets what the network says of it; without usable labels every
score is the share of label 1, or 0.5 if there is none; repeated rows and null ids are rows like others; of the columns
only doc_id and text are read, so names can't clash.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import labelled_sample, remainder, table, travels
from .textkit import LETTER, LOWER, SPACE, U, Slab, hash_runs, mix, runs, slabs, twice

travels(__name__)

#: Labelled documents that the network is fitted on, at most about; their tokens go to the driver.
TRAIN_DOCS = 6000
BITS = 15
DIM, ONES = 64, 4
HIDDEN = 24
NEAR = 2
#: Pairs of neighbours that are added up at a time; rows of sums that travel together; tasks whose sums meet first.
BLOCK, ROWS, SLOTS = 1 << 18, 1 << 10, 64
THRESHOLD = 0.7
#: Seeds of the signs' hashes: in capitals, said before, length, size of a text.
CAPITALS, AGAIN, LENGTH, SIZE = (U(k) << U(32) for k in (1, 2, 3, 4))


def bucket_of(h: np.ndarray) -> np.ndarray:
    return (mix(h) >> U(64 - BITS)).astype(np.int64)


def tokens(slab: Slab, signs: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the tokens of each text in order, and their texts; ``signs`` adds those of words and sizes."""
    buf = slab.buf
    letter = LETTER[buf]
    ls, le, lt = runs(letter, slab.off)
    ps, pe, pt = runs(~letter & ~SPACE[buf], slab.off)
    lh = hash_runs(LOWER[buf], ls, le)
    kinds = [(lh, lt, ls), (hash_runs(buf, ps, pe), pt, ps)]
    if signs:
        upper = np.r_[0, np.cumsum((buf >= 65) & (buf <= 90))]
        caps = (upper[le] - upper[ls] == le - ls) & (le - ls > 1)
        again, _ = twice(lh, lt)
        n = np.bincount(lt, minlength=len(slab)) + np.bincount(pt, minlength=len(slab))
        some = np.flatnonzero(n)
        level = np.floor(2 * np.log2(n[some])).astype(U)
        first = slab.off[some]
        kinds += [
            (np.full(int(caps.sum()), CAPITALS), lt[caps], ls[caps]), (np.full(int(again.sum()), AGAIN), lt[again], ls[again]),
            (LENGTH + np.minimum(le - ls, 24).astype(U), lt, ls), (SIZE + level, some, first),
        ]
    place = np.concatenate([k[2] for k in kinds])
    order = np.argsort(place, kind="stable")  # what starts at the same byte stays in the order of the kinds
    return bucket_of(np.concatenate([k[0] for k in kinds]))[order], np.concatenate([k[1] for k in kinds])[order]


def index_vectors() -> tuple[np.ndarray, np.ndarray]:
    """Places and signs of the ONES entries of each bucket's index vector."""
    x = mix(np.arange((1 << BITS) * ONES, dtype=U) + U(12345)).reshape(-1, ONES)
    return (x % U(DIM)).astype(np.int64), np.where((x >> U(40)) & U(1), 1.0, -1.0)


def neighbours(bucket: np.ndarray, owner: np.ndarray, total: np.ndarray) -> None:
    """Add the index vectors of each token's neighbours to the row of its bucket in ``total`` (buckets x DIM, whole)."""
    place, sign = index_vectors()
    cell = 2 * place + (sign < 0)  # the sign is a cell's last bit, so that counting is all there is to do
    for lo in range(0, len(owner), BLOCK):
        codes = []
        for d in range(1, NEAR + 1):
            hi = min(lo + BLOCK, len(owner) - d)
            same = owner[lo + d : hi + d] == owner[lo:hi]
            a, b = bucket[lo:hi][same], bucket[lo + d : hi + d][same]
            codes += [(2 * DIM * left)[:, None] + cell[right] for left, right in ((a, b), (b, a))]
        found = np.bincount(np.concatenate(codes).ravel(), minlength=2 * total.size)
        total += (found[0::2] - found[1::2]).reshape(total.shape)


def word_vectors(total: np.ndarray, seen: np.ndarray) -> np.ndarray:
    """Own index vector plus the sum of the neighbours' less what chance gives, each of unit length."""
    place, sign = index_vectors()
    context = total.astype(np.float64)
    context -= context.sum(0) / max(1, seen.sum()) * seen[:, None]
    context /= np.maximum(np.linalg.norm(context, axis=1, keepdims=True), 1e-9)
    own = np.zeros((1 << BITS, DIM))
    for k in range(ONES):
        own[np.arange(1 << BITS), place[:, k]] += sign[:, k] / ONES**0.5
    return (own + context).astype(np.float32)


def pool(vectors: np.ndarray, bucket: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    """The mean of the vectors of each text's tokens; zeros for a text without any."""
    out = np.zeros((n, vectors.shape[1]))
    if len(bucket):
        first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
        out[owner[first]] = np.add.reduceat(vectors[bucket], first, axis=0) / np.diff(np.r_[first, len(owner)])[:, None]
    return out


@dataclass
class Network:
    """Score = sigmoid(tanh(x W1 + b1) W2 + b2) at a temperature, for standardised x; ``flat`` if nothing was learned."""

    vectors: np.ndarray | None = None
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None
    w1: np.ndarray | None = None
    b1: np.ndarray | None = None
    w2: np.ndarray | None = None
    b2: float = 0.0
    heat: float = 1.0
    signs: bool = True
    flat: float = 0.5

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.tanh((x - self.mean) / self.scale @ self.w1 + self.b1) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.w1 is None:
            return np.full(len(x), self.flat)
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.heat, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, epochs: int = 60, rate: float = 0.01, decay: float = 1e-3, seed: int = 3) -> Network:
    """Minibatch Adam on seven eighths of the rows; the temperature comes from the others."""
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(x))
    held, used = order[: len(x) // 8], order[len(x) // 8 :]
    net = Network(mean=x[used].mean(0), scale=x[used].std(0) + 1e-6)
    net.w1, net.b1 = rng.normal(0, x.shape[1] ** -0.5, (x.shape[1], HIDDEN)), np.zeros(HIDDEN)
    net.w2 = rng.normal(0, HIDDEN**-0.5, HIDDEN)
    z = (x - net.mean) / net.scale
    state = [[np.zeros_like(p), np.zeros_like(p)] for p in (net.w1, net.b1, net.w2, np.zeros(1))]
    t = 0
    for _ in range(epochs):
        rng.shuffle(used)
        for lo in range(0, len(used), 128):
            rows = used[lo : lo + 128]
            h = np.tanh(z[rows] @ net.w1 + net.b1)
            err = (1 / (1 + np.exp(-np.clip(h @ net.w2 + net.b2, -30, 30))) - y[rows]) / len(rows)
            back = np.outer(err, net.w2) * (1 - h * h)
            grads = (z[rows].T @ back + decay * net.w1, back.sum(0), h.T @ err + decay * net.w2, np.array([err.sum()]))
            t += 1
            moves = []
            for g, s in zip(grads, state, strict=True):
                s[0][:] = 0.9 * s[0] + 0.1 * g
                s[1][:] = 0.999 * s[1] + 0.001 * g * g
                moves.append(rate * (s[0] / (1 - 0.9**t)) / (np.sqrt(s[1] / (1 - 0.999**t)) + 1e-8))
            net.w1, net.b1, net.w2, net.b2 = net.w1 - moves[0], net.b1 - moves[1], net.w2 - moves[2], net.b2 - float(moves[3][0])
    if len(held) > 20:
        logit, label = net.logits(x[held]), y[held]
        heats = np.exp(np.linspace(-1.0, 2.0, 61))
        loss = [np.logaddexp(0, np.where(label > 0, -1, 1) * logit / h).mean() for h in heats]
        net.heat = float(heats[int(np.argmin(loss))])
    return net


def learn_vectors(texts: DataFrame, signs: bool = True) -> np.ndarray:
    """The vectors of all buckets from every text of ``texts`` (text): whole sums, added up by task, by slot and at last by
    block of rows, so that the driver gets one table however many texts there are."""

    def work(batches):
        total, seen = np.zeros((1 << BITS, DIM), np.int64), np.zeros(1 << BITS, np.int64)
        for b in batches:
            for slab in slabs(b.column(0)):
                bucket, owner = tokens(slab, signs)
                neighbours(bucket, owner, total)
                seen += np.bincount(bucket, minlength=1 << BITS)
        if seen.any():
            both = np.concatenate([total, seen[:, None]], 1)
            blocks = [zlib.compress(both[lo : lo + ROWS].astype("<i8").view(np.uint8).reshape(-1, 8).T.tobytes(), 1) for lo in range(0, 1 << BITS, ROWS)]
            yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId() % SLOTS] * len(blocks), pa.int32()), pa.array(range(len(blocks)), pa.int32()), pa.array(blocks, pa.binary())], ["slot", "block", "sums"])

    def added(batches):
        total: dict[tuple[int, int], np.ndarray] = {}
        for b in batches:
            for slot, block, x in zip(*(c.to_pylist() for c in b.columns), strict=True):
                total[slot, block] = total.get((slot, block), 0) + np.frombuffer(zlib.decompress(x), np.uint8).reshape(8, -1).T.copy().view("<i8").ravel()
        for (slot, block), x in total.items():
            yield pa.RecordBatch.from_arrays([pa.array([slot], pa.int32()), pa.array([block], pa.int32()), pa.array([zlib.compress(x.view(np.uint8).reshape(-1, 8).T.tobytes(), 1)], pa.binary())], ["slot", "block", "sums"])

    schema = "slot int, block int, sums binary"
    parts = texts.select(F.col("text").cast("string")).mapInArrow(work, schema)
    parts = parts.repartition(SLOTS, "slot", "block").mapInArrow(added, schema).withColumn("slot", F.lit(0))
    both = np.zeros((1 << BITS, DIM + 1), np.int64)
    for r in parts.repartition(8, "block").mapInArrow(added, schema).collect():  # one table of buckets
        both[r["block"] * ROWS : (r["block"] + 1) * ROWS] = np.frombuffer(zlib.decompress(r["sums"]), np.uint8).reshape(8, -1).T.copy().view("<i8").reshape(-1, DIM + 1)
    return word_vectors(both[:, :DIM], both[:, DIM])


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_DOCS, modulus: int = 4, left_out: int = 2, signs: bool = True) -> Network:
    """Vectors from all texts outside the held-out fold; the network from about ``rows`` labelled ones of them."""

    def work(batches):
        for b in batches:
            for slab in slabs(b.column(0)):
                bucket, owner = tokens(slab, signs)
                cut = np.searchsorted(owner, np.arange(len(slab) + 1))
                rows_ = slice(slab.lo, slab.lo + len(slab))
                yield pa.RecordBatch.from_arrays([b.column(2)[rows_], b.column(1)[rows_], pa.array([bucket[cut[i] : cut[i + 1]].astype("<u2").tobytes() for i in range(len(slab))], pa.binary())], ["doc_id", "y", "tokens"])

    sample = labelled_sample(docs, labels, "quality", modulus, left_out, rows).select(F.col("text").cast("string"), "y", F.col("doc_id").cast("long"))
    got = sample.mapInArrow(work, "doc_id long, y int, tokens binary").toPandas().sort_values(["doc_id", "y"], kind="stable")
    y = got["y"].to_numpy(float)
    if len(y) == 0 or y.min() == y.max():
        return Network(flat=float(y[0]) if len(y) else 0.5)
    vectors = learn_vectors(docs.where(remainder("doc_id", modulus) != left_out), signs)
    x = np.zeros((len(y), DIM))
    for i, v in enumerate(got["tokens"]):
        bucket = np.frombuffer(v, "<u2").astype(np.int64)
        x[i] = pool(vectors, bucket, np.zeros(len(bucket), np.int64), 1)[0]
    net = fit(x, y)
    net.vectors, net.signs = vectors, signs
    return net


def score(docs: DataFrame, net: Network) -> DataFrame:
    """doc_id and score of every row."""
    kept = docs.sparkSession.sparkContext.broadcast(net)

    def work(batches):
        for b in batches:
            out = np.zeros(b.num_rows)
            for slab in slabs(b.column(1), 1 << 17):
                here = slice(slab.lo, slab.lo + len(slab))
                if kept.value.vectors is None:
                    out[here] = kept.value.flat
                else:
                    out[here] = kept.value.score(pool(kept.value.vectors, *tokens(slab, kept.value.signs), len(slab)))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out)], ["doc_id", "score"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(work, "doc_id long, score double")


def op9_random_indexing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, train(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", (remainder("doc_id", 4) == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
