"""Quality rules: a linear-chain conditional random field labels the lines of a text as content or boilerplate.

Lines are described by yes/no features (symbols, capitals, repetition, length, punctuation). The weights are fitted by
maximum likelihood on a bounded sample of ``labels``: the lines of documents of quality 1 count as content, those of
quality 0 as boilerplate; neighbouring lines inform each other through the transition weights. Viterbi decoding marks
the likeliest labels of a whole text, and the share of its word characters in content lines decides.

Defined cases: a null text has no words; lines without a word carry no label; without usable labels (none, or all
alike) the field keeps ``PRIOR_WEIGHTS``; repeated rows are judged alike; null ids are rows like others.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import labelled_sample, table, travels
from .textkit import SPACE, Slab, count_chars, hash_runs, per_text, runs, slabs, spans, twice, windows

travels(__name__)

#: Labelled documents that the field is fitted on, at most about.
TRAIN_DOCS = 4000
#: Content characters that a text must have, of 100.
SHARE = 50
MIN_WORDS = 10
MAX_REPEATED = 20

SYMBOL = np.zeros(256, bool)
SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True
UPPER = np.zeros(256, bool)
UPPER[65:91] = True
LOWER_ASCII = np.zeros(256, bool)
LOWER_ASCII[97:123] = True
DIGIT = np.zeros(256, bool)
DIGIT[48:58] = True
PUNCT = np.zeros(256, bool)
PUNCT[[ord(c) for c in "!?.,;:-_=+~^/\\()[]{}\"'@"]] = True

FEATURES = ("always", "some symbols", "many symbols", "symbols everywhere", "capitals", "copy of a line", "repeated words", "repeated throughout", "very short", "short", "long", "digits", "much punctuation", "ends a sentence", "starts as a sentence", "same as line before")
#: Weights for content where no labels are at hand: signs of boilerplate count against it.
PRIOR_WEIGHTS = np.array([2.0, -1.0, -2.0, -3.0, -3.0, -2.0, -1.0, -3.0, -0.5, 0.0, 0.5, -1.5, -1.5, 0.5, 0.0, -1.0])
PRIOR_STICK = 0.5


def measures(slab: Slab) -> dict[str, np.ndarray]:
    """Base counts of every text of a slab, and the features, texts and word characters of its worded lines."""
    n, buf, off = len(slab), slab.buf, slab.off
    ws, we, wt = runs(~SPACE[buf], off)
    chars = count_chars(buf, ws, we)
    h = hash_runs(buf, ws, we)
    win, at = windows(h, wt, 5)
    often, _ = twice(win, wt[at])
    edge = np.zeros(len(h) + 1, np.int64)
    np.add.at(edge, at[often], 1)
    np.add.at(edge, at[often] + 5, -1)
    repeated = np.cumsum(edge[:-1]) > 0

    ls, le, lt = runs(buf != 10, off)
    line_of = np.searchsorted(ls, ws, "right") - 1
    words = np.bincount(line_of, minlength=len(ls))
    has = words > 0
    keep = np.cumsum(has) - 1
    ls, le, lt, words = ls[has], le[has], lt[has], words[has]
    line_of = keep[line_of]
    m = len(ls)
    lh = hash_runs(buf, ls, le)
    _, copy = twice(lh, lt)
    lchars = np.bincount(line_of, weights=chars, minlength=m).astype(np.int64)
    lrep = np.bincount(line_of, weights=repeated, minlength=m)

    def share(flag):
        cum = np.zeros(len(buf) + 1, np.int64)
        np.cumsum(flag[buf], out=cum[1:])
        return cum[le] - cum[ls]

    symbols, upper, lower, digits, punct = (share(x) for x in (SYMBOL, UPPER, LOWER_ASCII, DIGIT, PUNCT))
    size = np.maximum(lchars, 1)
    last_byte = buf[we[np.r_[np.flatnonzero(np.diff(line_of)), len(line_of) - 1]] - 1] if m else np.zeros(0, np.uint8)
    first_byte = buf[ws[np.r_[0, np.flatnonzero(np.diff(line_of)) + 1]]] if m else np.zeros(0, np.uint8)
    same = np.zeros(m, bool)
    same[1:] = (lh[1:] == lh[:-1]) & (lt[1:] == lt[:-1])
    x = np.stack([
        np.ones(m, bool), symbols > 0, symbols * 20 > size, symbols * 8 > size, upper * 2 > upper + lower, copy,
        lrep * 10 > words, lrep * 2 > words, words < 3, words < 8, words > 30, digits * 5 > size, punct * 6 > size,
        (last_byte == 46) | (last_byte == 33) | (last_byte == 63), (first_byte < 97) | (first_byte > 122), same,
    ], 1).astype(np.float64) if m else np.zeros((0, len(FEATURES)))
    all_symbols = np.zeros(len(buf) + 1, np.int64)
    np.cumsum(SYMBOL[buf], out=all_symbols[1:])
    return {
        "n_words": per_text(None, wt, n), "word_chars": per_text(chars, wt, n), "n_symbols": all_symbols[off[1:]] - all_symbols[off[:-1]],
        "n_dup_lines": per_text(copy.astype(np.int64), lt, n), "n_repeat_words": per_text(repeated.astype(np.int64), wt, n),
        "x": x, "text": lt, "chars": lchars,
    }


# ---- the field: two states, 0 boilerplate and 1 content; only differences of their scores matter ---------------------


def lanes(text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First line and number of lines of each text that has any; ``text`` is ascending."""
    if not len(text):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = np.flatnonzero(np.r_[True, np.diff(text) != 0])
    return first, np.diff(np.r_[first, len(text)])


def viterbi(emit: np.ndarray, stick: np.ndarray, text: np.ndarray) -> np.ndarray:
    """The likeliest labels: ``emit`` scores content against boilerplate by line, ``stick[i, j]`` a step from i to j."""
    first, size = lanes(text)
    order = np.argsort(-size, kind="stable")
    first, size = first[order], size[order]
    back = np.zeros((len(emit), 2), np.int8)
    s0, s1 = np.zeros(len(first)), emit[first] if len(first) else np.zeros(0)
    for t in range(1, int(size[0]) if len(size) else 0):
        k = int(np.searchsorted(-size, -t, "left"))
        at = first[:k] + t
        a, b = s0[:k], s1[:k]
        c00, c10, c01, c11 = a + stick[0, 0], b + stick[1, 0], a + stick[0, 1], b + stick[1, 1]
        back[at, 0], back[at, 1] = c10 > c00, c11 >= c01
        s0[:k], s1[:k] = np.maximum(c00, c10), np.maximum(c01, c11) + emit[at]
    out = np.zeros(len(emit), np.int8)
    state = (s1 >= s0).astype(np.int8)
    for t in range(int(size[0]) - 1 if len(size) else -1, -1, -1):
        k = int(np.searchsorted(-size, -t, "left"))
        at = first[:k] + t
        out[at] = state[:k]
        state[:k] = back[at, state[:k]]
    return out


def fit(x: np.ndarray, y: np.ndarray, text: np.ndarray, rounds: int = 80, rate: float = 0.15, decay: float = 1e-3) -> tuple[np.ndarray, np.ndarray]:
    """Weights and transitions of maximum penalised likelihood; ``y`` are the labels of the lines of whole texts."""
    first, size = lanes(text)
    order = np.argsort(-size, kind="stable")
    first, size = first[order], size[order]
    steps = int(size[0])
    alive = [int(np.searchsorted(-size, -t, "left")) for t in range(steps)]
    theta = np.zeros(x.shape[1] + 4)
    m1, m2 = np.zeros_like(theta), np.zeros_like(theta)
    seen_step = np.zeros((2, 2))
    same_text = np.flatnonzero(text[1:] == text[:-1])
    np.add.at(seen_step, (y[same_text], y[same_text + 1]), 1)
    target = np.r_[x.T @ y, seen_step.ravel()]
    for it in range(1, rounds + 1):
        emit, stick = x @ theta[:-4], theta[-4:].reshape(2, 2)
        alpha = np.zeros((len(x), 2))
        alpha[first, 1] = emit[first]
        for t in range(1, steps):
            at = first[: alive[t]] + t
            p = alpha[at - 1]
            alpha[at] = np.logaddexp(p[:, :1] + stick[0], p[:, 1:] + stick[1])
            alpha[at, 1] += emit[at]
        beta = np.zeros((len(x), 2))
        expected = np.zeros((2, 2))
        for t in range(steps - 1, 0, -1):
            at = first[: alive[t]] + t
            nxt = beta[at] + np.stack([np.zeros(len(at)), emit[at]], 1)
            beta[at - 1] = np.logaddexp(stick[:, 0] + nxt[:, :1], stick[:, 1] + nxt[:, 1:])
            joint = alpha[at - 1][:, :, None] + stick + nxt[:, None, :]
            z = np.logaddexp(alpha[at, 0] + beta[at, 0], alpha[at, 1] + beta[at, 1])
            expected += np.exp(joint - z[:, None, None]).sum(0)
        content = 1 / (1 + np.exp(alpha[:, 0] + beta[:, 0] - alpha[:, 1] - beta[:, 1]))
        grad = (target - np.r_[x.T @ content, expected.ravel()]) / len(x) - decay * theta
        m1, m2 = 0.9 * m1 + 0.1 * grad, 0.99 * m2 + 0.01 * grad**2
        theta = theta + rate * (m1 / (1 - 0.9**it)) / (np.sqrt(m2 / (1 - 0.99**it)) + 1e-8)
    return theta[:-4], theta[-4:].reshape(2, 2)


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_DOCS) -> tuple[np.ndarray, np.ndarray]:
    """Fit the field on the lines of about ``rows`` labelled documents; their features, not texts, reach the driver."""
    sample = labelled_sample(docs, labels, "quality", 1, -1, rows)

    def work(batches):
        for b in batches:
            y = b.column(1).to_numpy()
            doc = b.column(2).to_pylist()
            for slab in slabs(b.column(0)):
                m = measures(slab)
                bits = (m["x"].astype(np.int64) << np.arange(len(FEATURES))).sum(1)
                cut = np.searchsorted(m["text"], np.arange(len(slab) + 1))
                ids = [doc[slab.lo + i] for i in range(len(slab))]
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(y[slab.lo : slab.lo + len(slab)], pa.int32()), pa.array([bits[cut[i] : cut[i + 1]].tolist() for i in range(len(slab))], pa.list_(pa.int64()))], ["doc_id", "y", "lines"])

    got = sample.select(F.col("text").cast("string"), "y", "doc_id").mapInArrow(work, "doc_id long, y int, lines array<long>").toPandas().sort_values(["doc_id", "y"])
    got = got[got["lines"].map(len) > 0]
    prior = PRIOR_WEIGHTS, np.array([[PRIOR_STICK, 0.0], [0.0, PRIOR_STICK]])
    if got["y"].nunique() < 2:
        return prior
    bits = np.concatenate([np.asarray(v, np.int64) for v in got["lines"]])
    size = np.array([len(v) for v in got["lines"]])
    x = ((bits[:, None] >> np.arange(len(FEATURES))) & 1).astype(float)
    text = np.repeat(np.arange(len(size)), size)
    return fit(x, np.repeat(got["y"].to_numpy(), size).astype(np.int64), text)


def judge(docs: DataFrame, weights: np.ndarray, stick: np.ndarray, share: int = SHARE) -> DataFrame:
    """The base counts of every row and whether it is kept; content_chars and n_lines come along."""

    def work(batches):
        for b in batches:
            for slab in slabs(b.column(1)):
                m = measures(slab)
                n = len(slab)
                label = viterbi(m["x"] @ weights, stick, m["text"])
                content = per_text(m["chars"] * label.astype(np.int64), m["text"], n)
                failed = (m["n_words"] < MIN_WORDS) | (100 * m["n_repeat_words"] > MAX_REPEATED * m["n_words"])
                kept = ~failed & (100 * content >= share * m["word_chars"])
                base = [pa.array(m[c].astype(np.int64)) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")]
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(slab.lo, n), *base, pa.array(failed), pa.array(kept), pa.array(content), pa.array(per_text(None, m["text"], n).astype(np.int64))],
                    ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "content_chars", "n_lines"],
                )

    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, content_chars long, n_lines long"
    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(work, schema)


def keep_good(docs: DataFrame, weights: np.ndarray, stick: np.ndarray, share: int = SHARE) -> DataFrame:
    """The rows of ``docs`` that the rules keep, with all their columns."""
    at = docs.columns.index("text")

    def work(batches):
        for b in batches:
            mask = np.zeros(b.num_rows, bool)
            for slab in slabs(b.column(at)):
                m = measures(slab)
                label = viterbi(m["x"] @ weights, stick, m["text"])
                content = per_text(m["chars"] * label.astype(np.int64), m["text"], len(slab))
                failed = (m["n_words"] < MIN_WORDS) | (100 * m["n_repeat_words"] > MAX_REPEATED * m["n_words"])
                mask[slab.lo : slab.lo + len(slab)] = ~failed & (100 * content >= share * m["word_chars"])
            yield b.filter(pa.array(mask))

    return docs.mapInArrow(work, docs.schema)


def op5_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return judge(docs, *train(docs, table(spark, sf_dir, "labels")))
