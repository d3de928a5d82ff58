"""A gated recurrent language model over words, and the unigram base that it is held against.

Counts of all training words are exact, by 64-bit word hash. The commonest ``WORDS`` words (with the end mark) are the
network's own; the output is factored into classes, small ones of frequent words and large ones of rarer words, and
words within a class; one more class holds every other word, by smoothed counts inside it, so that a text's probability is whole. Training is truncated
backpropagation in numpy over every training text, each read once: the texts are dealt into ``ROUNDS``; in each round
every partition goes on from the same weights over its texts of that round, and the weights that they end with are
averaged, tree-wise. Scoring carries the state through a text from its first word to its last, many texts side by side,
window after window.

Words beyond a broadcast head of the counts (bounded by ``HEAD``) meet their counts in a join.

Defined cases: a null or empty text is its end mark alone; without training texts every word is unknown and the
network spreads evenly; repeated rows and null ids are rows like others, and each row is scored by itself.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import remainder, staged, table, travels
from .textkit import LOWER, SPACE, Slab, hash_runs, per_text, runs, slabs, spans

travels(__name__)

#: Words of the network, the end mark included; their classes; width of the state and of a word's entry.
WORDS, CLASSES, STATE, ENTRY = 4096, 48, 24, 16
#: Rounds that all training texts are dealt into; steps of a window; texts side by side.
ROUNDS, WINDOW, LANES = 3, 24, 384
#: Words of the texts that a task shuffles and trains on at a time; partitions whose weights one group adds up.
CHUNK, FAN = 1 << 20, 16
#: Outputs that scoring works out together, at least.
BLOCK = 4096
#: Rows and bytes of texts that are scored together, at most about.
POOL, POOL_BYTES = 8000, 1 << 25
#: Largest exponent for which sums of exponentials stay numbers of single precision, with room for many terms.
BOUND = 60
#: Most words whose counts are broadcast (16 bytes each).
HEAD = 1 << 19
SMOOTH = 0.1
REST = WORDS  # the id of every word that isn't the network's own
END = 0


def words(slab: Slab) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes and their texts."""
    buf = LOWER[slab.buf]
    s, e, t = runs(~SPACE[buf], slab.off)
    return hash_runs(buf, s, e).view(np.int64), t


def count_words(docs: DataFrame) -> DataFrame:
    """(h, c): how often each word occurs in all texts."""

    def work(batches):
        hs, cs, n = [], [], 0

        def merged():
            h, c = np.concatenate(hs), np.concatenate(cs)
            order = np.argsort(h, kind="stable")
            h, c = h[order], c[order]
            first = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            return h[first], np.add.reduceat(c, first)

        for b in batches:
            for slab in slabs(b.column(0), 1 << 21):
                h, c = np.unique(words(slab)[0], return_counts=True)
                hs.append(h)
                cs.append(c)
                n += len(h)
                if n > 1_500_000:
                    h, c = merged()
                    if len(h) > 1_000_000:
                        yield pa.RecordBatch.from_arrays([pa.array(h), pa.array(c)], ["h", "c"])
                        hs, cs, n = [], [], 0
                    else:
                        hs, cs, n = [h], [c], len(h)
        if n:
            h, c = merged()
            for lo in range(0, len(h), 100_000):
                yield pa.RecordBatch.from_arrays([pa.array(h[lo : lo + 100_000]), pa.array(c[lo : lo + 100_000])], ["h", "c"])

    parts = docs.select(F.col("text").cast("string")).mapInArrow(work, "h long, c long")
    return parts.groupBy("h").agg(F.sum("c").alias("c"))


# ---- the network ----------------------------------------------------------------------------------------------------


class Network:
    """Entries, gates and factored outputs; words are ids by rank, END the first and REST the last."""

    def __init__(self, n_words: int, seed: int = 5):
        rng = np.random.default_rng(seed)
        self.n_words = n_words
        self.used = min(CLASSES, n_words)  # classes that have words: their borders go with the square, as ranks get rarer
        edges = np.floor((np.arange(self.used + 1) / self.used) ** 2 * n_words).astype(int)
        self.edges = np.maximum(edges, np.arange(self.used + 1))
        self.cls = np.full(WORDS + 1, CLASSES)
        self.cls[:n_words] = np.repeat(np.arange(self.used), np.diff(self.edges))
        f = np.float32
        self.p = {
            "entry": rng.normal(0, 0.3, (WORDS + 1, ENTRY)).astype(f), "wx": rng.normal(0, ENTRY**-0.5, (ENTRY, 3 * STATE)).astype(f),
            "wh": rng.normal(0, STATE**-0.5, (STATE, 3 * STATE)).astype(f), "b": np.zeros(3 * STATE, f),
            "wc": rng.normal(0, 0.1, (STATE, CLASSES + 1)).astype(f), "bc": np.zeros(CLASSES + 1, f),
            "wo": rng.normal(0, 0.1, (WORDS, STATE)).astype(f), "bo": np.zeros(WORDS, f),
        }
        self.moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in self.p.items()}
        self.t = 0

    def step(self, gate_x: np.ndarray, h: np.ndarray) -> tuple:
        s = STATE
        gh = h @ self.p["wh"]
        zr = gate_x[:, : 2 * s] + gh[:, : 2 * s]
        zr *= np.float32(0.5)  # the logistic function by the hyperbolic tangent
        np.tanh(zr, out=zr)
        zr += 1
        zr *= np.float32(0.5)
        z, r = zr[:, :s], zr[:, s:]
        n = r * gh[:, 2 * s :]
        n += gate_x[:, 2 * s :]
        np.tanh(n, out=n)
        new = h - n
        new *= z
        new += n
        return new, z, r, n, gh[:, 2 * s :]

    def outputs(self, h: np.ndarray, ids: np.ndarray, learn: bool = False):
        """Natural log-probability of each id after each state; with ``learn`` also gradients."""
        p = self.p
        # by class from the start, so that what belongs to a class lies together and none of it is gathered again
        order = np.argsort(self.cls[ids].astype(np.uint8), kind="stable")
        h, ids = h[order], ids[order]
        cls = self.cls[ids]
        cut = np.searchsorted(cls, np.arange(CLASSES + 1))
        # no part of a state exceeds 1, so the weights bound what the exponential sees; small bounds need no maxima
        wide = np.abs(p["wc"]).sum(0) + np.abs(p["bc"]) > BOUND
        widest = np.abs(p["wo"]).sum(1) + np.abs(p["bo"]) > BOUND
        ex = h @ p["wc"]
        ex += p["bc"]
        if self.used < CLASSES:
            ex[:, self.used : CLASSES] = -1e9
        if wide.any():
            ex -= ex.max(1, keepdims=True)
        rows = np.arange(len(ids))
        out = ex[rows, cls]
        np.exp(ex, out=ex)
        total = ex @ np.ones(ex.shape[1], np.float32)
        out = out - np.log(total)
        if learn:
            ex *= (1 / total)[:, None]
            ex[rows, cls] -= 1
            grads = {"wc": h.T @ ex, "bc": ex.sum(0), "wo": np.zeros_like(p["wo"]), "bo": np.zeros_like(p["bo"])}
            dh = ex @ p["wc"].T
        for k in range(self.used):
            lo, hi = self.edges[k], self.edges[k + 1]
            mine = slice(cut[k], cut[k + 1])
            if cut[k] == cut[k + 1] or hi - lo == 1:  # a word alone in its class is certain there
                continue
            x = h[mine]
            ex = x @ p["wo"][lo:hi].T
            ex += p["bo"][lo:hi]
            if widest[lo:hi].any():
                ex -= ex.max(1, keepdims=True)
            at = ids[mine] - lo
            sub = rows[: len(at)]
            got = ex[sub, at]
            np.exp(ex, out=ex)
            total = ex @ np.ones(hi - lo, np.float32)
            out[mine] += got - np.log(total)
            if learn:
                ex *= (1 / total)[:, None]
                ex[sub, at] -= 1
                grads["wo"][lo:hi] = ex.T @ x
                grads["bo"][lo:hi] = ex.sum(0)
                dh[mine] += ex @ p["wo"][lo:hi]
        back = np.empty_like(out)
        back[order] = out
        if not learn:
            return back
        down = np.empty_like(dh)
        down[order] = dh
        return back, grads, down

    def train_window(self, ids: np.ndarray, prev: np.ndarray, h: np.ndarray, rate: float) -> np.ndarray:
        """One window of truncated backpropagation; ``ids`` and ``prev`` are steps by lanes. Returns the last state."""
        p, s, (steps, lanes) = self.p, STATE, ids.shape
        x = p["entry"][prev.ravel()]
        gx = (x @ p["wx"] + p["b"]).reshape(steps, lanes, 3 * s)
        alive = (prev != END).astype(np.float32)[:, :, None]
        was, z, r, n, ghn, out = (np.empty((steps, lanes, s), np.float32) for _ in range(6))
        for t in range(steps):
            was[t] = h * alive[t]
            out[t], z[t], r[t], n[t], ghn[t] = self.step(gx[t], was[t])
            h = out[t]
        _, g, dout = self.outputs(out.reshape(-1, s), ids.ravel(), learn=True)
        dout = dout.reshape(steps, lanes, s)
        # what each step's state passes to its gates, but for the gradient that comes from later steps
        to_n = (1 - z) * (1 - n * n)
        to_z = (was - n) * z * (1 - z)
        to_r = ghn * r * (1 - r)
        dgh = np.empty((steps, lanes, 3 * s), np.float32)
        d = np.empty_like(dgh)
        back = np.ascontiguousarray(p["wh"].T)
        carry = np.zeros_like(h)
        for t in range(steps - 1, -1, -1):
            dh = dout[t] + carry
            dn = dh * to_n[t]
            np.multiply(dh, to_z[t], out=dgh[t, :, :s])
            np.multiply(dn, to_r[t], out=dgh[t, :, s : 2 * s])
            np.multiply(dn, r[t], out=dgh[t, :, 2 * s :])
            d[t, :, 2 * s :] = dn
            carry = dgh[t] @ back
            dh *= z[t]
            carry += dh
            carry *= alive[t]
        d[:, :, : 2 * s] = dgh[:, :, : 2 * s]
        g["wh"] = was.reshape(-1, s).T @ dgh.reshape(-1, 3 * s)
        d = d.reshape(-1, 3 * s)
        g["wx"], g["b"] = x.T @ d, d.sum(0)
        dx = d @ p["wx"].T
        order = np.argsort(prev.ravel().astype(np.uint16), kind="stable")
        there = prev.ravel()[order]
        first = np.flatnonzero(np.r_[True, there[1:] != there[:-1]])
        g["entry"] = np.zeros_like(p["entry"])
        g["entry"][there[first]] = np.add.reduceat(dx[order], first, axis=0)
        self.t += 1
        for k, v in g.items():
            v *= np.float32(1 / ids.size)
            m1, m2 = self.moments[k]
            m1 += np.float32(0.1) * (v - m1)
            v *= v
            v -= m2
            m2 += np.float32(0.001) * v
            p[k] -= np.float32(rate / (1 - 0.9**self.t)) * m1 / (np.sqrt(m2 * np.float32(1 / (1 - 0.999**self.t))) + np.float32(1e-6))
        return h

    def score(self, ids: np.ndarray, off: np.ndarray, lanes: int = 512) -> np.ndarray:
        """Natural log-probability of each text; ``ids[off[i]:off[i + 1]]`` are its words and the end mark."""
        size = np.diff(off)
        out = np.zeros(len(size))
        order = np.argsort(-size, kind="stable")
        table_ = self.p["entry"] @ self.p["wx"] + self.p["b"]
        for lo in range(0, len(order), lanes):
            mine = order[lo : lo + lanes]
            n, base = size[mine], off[mine]
            h = np.zeros((len(mine), STATE), np.float32)
            prev = np.full(len(mine), END)
            t0 = 0
            while t0 < int(n[0]):
                hs, goal, who = [], [], []
                # the fewer texts go on, the more steps share the work on outputs
                t1 = t0 + max(WINDOW, BLOCK // int(np.searchsorted(-n, -t0, "left")))
                for t in range(t0, min(t1, int(n[0]))):
                    k = int(np.searchsorted(-n, -t, "left"))
                    h, prev = h[:k], prev[:k]
                    h = self.step(table_[prev], h)[0]
                    prev = ids[base[:k] + t].astype(np.int64)
                    hs.append(h)
                    goal.append(prev)
                    who.append(k)
                t0 = t1
                got = self.outputs(np.concatenate(hs), np.concatenate(goal))
                owner = np.concatenate([np.arange(k) for k in who])
                out[mine] += np.bincount(owner, weights=got, minlength=len(mine))
        return out


def start(count: np.ndarray, n_words: int, seed: int = 5) -> Network:
    """A network that knows how often each id occurs (``count``) and no more; without texts it spreads evenly."""
    net = Network(n_words, seed)
    if not count.sum():
        for k in ("wc", "bc", "wo", "bo"):
            net.p[k][:] = 0
        return net
    c = count + 0.5
    net.p["bc"][: net.used] = np.log(np.add.reduceat(c[:n_words], net.edges[:-1]))
    net.p["bc"][CLASSES] = np.log(c[REST])
    net.p["bc"] -= net.p["bc"][[*range(net.used), CLASSES]].mean()
    net.p["bo"][:] = np.log(c[:WORDS])
    net.p["bo"] -= net.p["bo"][:n_words].mean()
    return net


def learn(net: Network, texts: list[np.ndarray], rate: float, rng: np.random.Generator) -> np.ndarray:
    """Train once over texts of word ids that end in END. Returns how often each id occurs."""
    stream = np.concatenate([texts[i] for i in rng.permutation(len(texts))]).astype(np.int64)
    lanes = max(1, min(LANES, len(stream) // (32 * WINDOW)))
    each = -(-len(stream) // lanes)
    ids = np.resize(stream, lanes * each).reshape(lanes, each).T  # the last lane is filled up from the stream's start
    prev = np.concatenate([np.full((1, lanes), END), ids[:-1]])
    h = np.zeros((lanes, STATE), np.float32)
    for t in range(0, each, WINDOW):
        h = net.train_window(ids[t : t + WINDOW], prev[t : t + WINDOW], h, rate)
    return np.bincount(stream, minlength=WORDS + 1)


def weights(net: Network, count: np.ndarray) -> dict[str, np.ndarray]:
    """How much a network that saw the ids ``count`` times says about each row of its parameters.

    A word's entry counts by the word and its output by its class, so that a word of few partitions isn't thinned out
    by the others, which leave it where it was."""
    by_class = np.add.reduceat(count[: net.n_words].astype(float), net.edges[:-1])
    out = np.zeros(WORDS)
    out[: net.n_words] = by_class[net.cls[: net.n_words]]
    return {k: {"entry": count[:, None], "wo": out[:, None], "bo": out}.get(k, float(count.sum())) for k in net.p}


# ---- corpus ---------------------------------------------------------------------------------------------------------


@dataclass
class Totals:
    """What all rows share: N and V with the end mark, its count, and the smoothed mass of words not the network's."""

    n: int
    v: int
    ends: int
    rest: float


def corpus(train: DataFrame) -> tuple[DataFrame, Totals, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Counts (stored), totals, the network's word hashes by rank, the counts of its ids, and the head's hashes
    (ascending) and counts."""
    counts = staged(count_words(train), "counts")
    ends = train.count()
    level = F.floor(F.log2("c") * 8).cast("int")
    steps = counts.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("k"), F.sum("c").alias("c")).orderBy(F.desc("level")).collect()
    n, v = sum(r["c"] for r in steps) + ends, sum(r["k"] for r in steps) + (ends > 0)
    room, floor_ = HEAD, None
    for r in steps:
        if r["k"] > room:
            break
        room, floor_ = room - r["k"], r["level"]
    head = counts.where(level >= floor_).toPandas() if floor_ is not None else None  # at most HEAD rows
    hh, hc = (np.zeros(0, np.int64),) * 2 if head is None else (head["h"].to_numpy(), head["c"].to_numpy())
    order = np.argsort(hh)
    hh, hc = hh[order], hc[order]
    top = counts.orderBy(F.desc("c"), "h").limit(WORDS - 1).collect()
    own = np.array([r["h"] for r in top], np.int64)
    rest = n - ends - sum(r["c"] for r in top)
    seen = np.zeros(WORDS + 1)
    seen[: len(top) + 1], seen[REST] = [ends, *(r["c"] for r in top)], rest
    return counts, Totals(n, v, ends, float(rest + SMOOTH * (v - (ends > 0) - len(top) + 1))), own, seen, hh, hc


def counted(h: np.ndarray, head: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which words are in the head of the counts, and the logarithms of their smoothed counts, 0 for others."""
    if not len(head):
        return np.zeros(len(h), bool), np.zeros(len(h))
    at = np.minimum(np.searchsorted(head, h), len(head) - 1)
    found = head[at] == h
    return found, np.where(found, np.log10(count[at] + SMOOTH), 0.0)


def ids_of(h: np.ndarray, owner: np.ndarray, n_texts: int, own_sorted: np.ndarray, own_id: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Network ids of all words with END after each text, and the texts' offsets."""
    if len(own_sorted):
        at = np.minimum(np.searchsorted(own_sorted, h), len(own_sorted) - 1)
        ids = np.where(own_sorted[at] == h, own_id[at], REST)
    else:
        ids = np.full(len(h), REST)
    size = np.bincount(owner, minlength=n_texts)
    off = spans(size + 1)
    out = np.full(off[-1], END, np.int16)
    out[np.arange(len(h)) + owner] = ids
    return out, off


def word_ids(train: DataFrame, own: np.ndarray) -> DataFrame:
    """(round, ids): the round that each row is dealt to, and the network's ids of its words, as 16-bit integers."""
    order = np.argsort(own)
    own_sorted, own_id = own[order], order + 1

    def work(batches):
        at = TaskContext.get().partitionId()
        for b in batches:
            for slab in slabs(b.column(0)):
                n = len(slab)
                ids, off = ids_of(*words(slab), n, own_sorted, own_id)
                ids = [ids[off[i] : off[i + 1]].astype("<i2").tobytes() for i in range(n)]
                yield pa.RecordBatch.from_arrays([pa.array((at + np.arange(n)) % ROUNDS, pa.int32()), pa.array(ids, pa.binary())], ["round", "ids"])
                at += n

    return train.select(F.col("text").cast("string")).mapInArrow(work, "round int, ids binary")


def one_round(texts: DataFrame, net: Network, rate: float, seed: int) -> np.ndarray:
    """Train on ``texts``, each partition by itself from ``net``, which then takes the averaged weights. Returns how
    often each id was seen."""
    kept = texts.sparkSession.sparkContext.broadcast((net.p, net.n_words))

    def work(batches):
        p, n_words = kept.value
        mine, part = Network(n_words), TaskContext.get().partitionId()
        mine.p = {k: v.copy() for k, v in p.items()}
        rng = np.random.default_rng((seed, part))
        held, n, count = [], 0, np.zeros(WORDS + 1, np.int64)
        for b in batches:
            for x in b.column(0):
                held.append(np.frombuffer(x.as_py(), "<i2"))
                n += len(held[-1])
                if n >= CHUNK:
                    count += learn(mine, held, rate, rng)
                    held, n = [], 0
        if n:
            count += learn(mine, held, rate, rng)
        if count.sum():
            by = weights(mine, count)
            sums = np.concatenate([(v * by[k]).ravel() for k, v in mine.p.items()] + [count])
            yield pa.RecordBatch.from_arrays([pa.array([part // FAN]), pa.array([sums.astype("<f8").tobytes()], pa.binary())], ["slot", "sums"])

    def added(t: pa.Table) -> pa.Table:
        total = sum(np.frombuffer(x.as_py(), "<f8") for x in t.column("sums"))
        return pa.table({"slot": pa.array([t.column("slot")[0].as_py() // FAN]), "sums": pa.array([total.tobytes()], pa.binary())})

    parts = texts.select("ids").mapInArrow(work, "slot long, sums binary")
    width = -(-texts.rdd.getNumPartitions() // FAN)
    while True:  # at most FAN rows reach the driver, however many partitions trained
        parts = parts.groupBy("slot").applyInArrow(added, "slot long, sums binary")
        if width <= FAN:
            break
        width = -(-width // FAN)
    got = parts.collect()
    if not got:
        return np.zeros(WORDS + 1)
    total = sum(np.frombuffer(r["sums"], "<f8") for r in got)
    count, at = total[-WORDS - 1 :], 0
    by = weights(net, count)
    for k, v in net.p.items():
        w = np.broadcast_to(by[k], v.shape)
        mean = total[at : at + v.size].reshape(v.shape) / np.maximum(w, 1)
        net.p[k] = np.where(w > 0, mean, v).astype(np.float32)
        at += v.size
    return count


def train_network(train: DataFrame, own: np.ndarray, seen: np.ndarray, rate: float = 0.02, seed: int = 5) -> Network:
    """The network after every row of ``train`` was learned from once."""
    net = start(seen, len(own) + 1, seed)
    if seen.sum():
        texts = staged(word_ids(train, own), "ids", "round")
        for k in range(ROUNDS):
            one_round(texts.where(F.col("round") == k), net, rate * 0.7**k, seed + k)
    return net


def pooled(batches):
    """Batches put together to ``POOL`` rows or ``POOL_BYTES``: the longest texts of more rows go on side by side."""
    kept, rows, size = [], 0, 0
    for b in batches:
        if kept and size + b.nbytes > POOL_BYTES:
            yield pa.Table.from_batches(kept).combine_chunks().to_batches()[0]
            kept, rows, size = [], 0, 0
        if b.num_rows:
            kept.append(b)
            rows, size = rows + b.num_rows, size + b.nbytes
        if rows >= POOL:
            yield pa.Table.from_batches(kept).combine_chunks().to_batches()[0]
            kept, rows, size = [], 0, 0
    if kept:
        yield pa.Table.from_batches(kept).combine_chunks().to_batches()[0]


TAIL = pa.list_(pa.struct([("h", pa.int64()), ("k", pa.int32())]))
SCORED = "row long, doc_id long, held_out boolean, n_tokens long, n_known long, base double, model double, n_rest long, rest_log double, tail array<struct<h:long,k:int>>"


def row_scores(docs: DataFrame, totals: Totals, own: np.ndarray, head: np.ndarray, head_count: np.ndarray, net: Network) -> DataFrame:
    """Per row all that its own words say; words beyond the head are listed in ``tail`` with their times."""
    order = np.argsort(own)
    kept = docs.sparkSession.sparkContext.broadcast((own[order], order + 1, head, head_count, net))

    def work(batches):
        own_sorted, own_id, hh, hc, model = kept.value
        row = TaskContext.get().partitionId() << 33
        end_log = np.log10(totals.ends + SMOOTH)
        own_found, own_log = np.zeros(WORDS + 1, bool), np.zeros(WORDS + 1)  # by id, so that only other words are looked for
        own_found[own_id], own_log[own_id] = counted(own_sorted, hh, hc)
        for b in pooled(batches):
            m = b.num_rows
            ids_all, sizes = [], []
            cols = {c: np.zeros(m) for c in ("n", "known", "base", "n_rest", "rest")}
            tail_h, tail_k, tail_n = [], [], []
            for slab in slabs(b.column(2)):
                h, owner = words(slab)
                n = len(slab)
                ids, off = ids_of(h, owner, n, own_sorted, own_id)
                ids_all.append(ids)
                sizes.append(np.diff(off))
                here = slice(slab.lo, slab.lo + n)
                mine = ids[np.arange(len(h)) + owner]
                rest = mine == REST
                found, logc = own_found[mine], own_log[mine]
                others = np.flatnonzero(rest)
                found[others], logc[others] = counted(h[others], hh, hc)
                cols["n"][here] = per_text(None, owner, n) + 1
                cols["known"][here] = per_text(found.astype(np.int64), owner, n) + (totals.ends > 0)
                cols["base"][here] = per_text(logc, owner, n) + end_log
                cols["n_rest"][here] = per_text(rest.astype(np.int64), owner, n)
                cols["rest"][here] = per_text(np.where(rest, logc, 0.0), owner, n)
                far = np.flatnonzero(~found)
                h, owner = h[far], owner[far]
                order_ = np.lexsort((h, owner))
                h, owner = h[order_], owner[order_]
                first = np.flatnonzero(np.r_[True, (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])][: len(h)])
                tail_h.append(h[first])
                tail_k.append(np.diff(np.r_[first, len(h)]).astype(np.int32))
                tail_n.append(np.bincount(owner[first], minlength=n))
            model_log = model.score(np.concatenate(ids_all), spans(np.concatenate(sizes))) / np.log(10) if m else np.zeros(0)
            whole = lambda c: pa.array(cols[c].astype(np.int64))
            if m:
                items = pa.StructArray.from_arrays([pa.array(np.concatenate(tail_h)), pa.array(np.concatenate(tail_k))], ["h", "k"])
                tails = pa.ListArray.from_arrays(pa.array(spans(np.concatenate(tail_n)).astype(np.int32)), items)
            else:
                tails = pa.array([], TAIL)
            yield pa.RecordBatch.from_arrays(
                [pa.array(row + np.arange(m)), b.column(0), b.column(1), whole("n"), whole("known"), pa.array(cols["base"]), pa.array(model_log), whole("n_rest"), pa.array(cols["rest"]), tails],
                ["row", "doc_id", "held_out", "n_tokens", "n_known", "base", "model", "n_rest", "rest_log", "tail"],
            )
            row += m

    return docs.select(F.col("doc_id").cast("long"), (remainder("doc_id", 10) == 0).alias("held_out"), F.col("text").cast("string")).mapInArrow(work, SCORED)


def language_model(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row of ``docs`` (doc_id, text)."""
    train = docs.where(remainder("doc_id", 10) != 0)
    counts, totals, own, seen, head, head_count = corpus(train)
    net = train_network(train, own, seen)
    rows = staged(row_scores(docs, totals, own, head, head_count, net), "scored")
    far = rows.select("row", F.inline("tail")).join(counts, "h", "left").select("row", "k", F.coalesce("c", F.lit(0)).alias("c"))
    far = far.groupBy("row").agg(
        F.sum(F.when(F.col("c") > 0, F.col("k")).otherwise(0)).alias("far_known"), F.sum(F.col("k") * F.log10(F.col("c") + SMOOTH)).alias("far_log"),
    )
    per_token = float(np.log10(totals.n + SMOOTH * (totals.v + 1)))
    per_rest = float(np.log10(totals.rest))
    far_log = F.coalesce("far_log", F.lit(0.0))
    return rows.join(far, "row", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("far_known", F.lit(0))).cast("long").alias("n_known"), F.lit(totals.n).cast("long").alias("train_tokens"),
        (F.col("base") + far_log - F.col("n_tokens") * per_token).alias("base_score"),
        (F.col("model") + F.col("rest_log") + far_log - F.col("n_rest") * per_rest).alias("score"),
    )


def op10_gru_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_model(table(spark, sf_dir, "documents"))
