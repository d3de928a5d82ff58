"""Best-fit packing of token sequences by patterns.

Documents become pieces of at most ``size`` tokens. The histogram of piece lengths (at most ``size`` numbers, whatever
the corpus) goes to the driver, which enumerates patterns of up to ``depth`` lengths that fill a sequence exactly,
fits how often each is used by non-negative least squares, rounds down, and packs what is left over by best fit on
the counts. The finished plan is a table of slots by length; each piece takes the slot of its rank among the pieces of
its length.

Defined cases: a null text is an empty one, of one token (the end token); null and repeated ids are rows like others;
an empty table gives no rows; columns beside doc_id and text are ignored.
"""

from __future__ import annotations

import unicodedata
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import staged, stash, table, travels
from .textkit import U, hash_runs, slabs, spans

travels(__name__)

END_ID = 2
SIZE = 1024
#: Ranks within a length are counted in parts, so that a length with a third of all pieces is spread: at least so many
#: parts, and as many that each holds about PART_ROWS pieces at most.
PARTS, PART_ROWS = 256, 1_000_000

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


# ---- tokens -----------------------------------------------------------------------------------------------------


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class Encoder:
    """Ids of whole texts by a byte-level BPE file of the ``tokenizers`` library.

    Its merges never cross the borders of pre-tokens, so ids are looked up by pre-token: a vectorised pass cuts the
    texts, and the library's model encodes each distinct pre-token once. Texts with a character of no known kind go
    through the library as they are."""

    SLOTS = 1 << 19
    MOST = 400_000

    def __init__(self, path: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.model = self.tokenizer.model
        self.model._resize_cache(0)  # words come once each
        # byte-level vocabularies write bytes as characters: printable ones as themselves, the others from 256 on
        shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in set(shown)]
        self.letters = {b: b for b in shown} | {b: 256 + i for i, b in enumerate(rest)}
        # classes: 1 letter, 2 number, 3 white space, 4 other, 0 for the library
        self.kind = np.zeros(0x2060, np.uint8)
        for c in [*range(0x530), *range(0x2010, 0x2028), *range(0x2030, 0x205F)]:
            k = unicodedata.category(chr(c))[0]
            self.kind[c] = 0 if k == "C" and c > 0x9F else {"L": 1, "N": 2}.get(k, 4)
        self.kind[[9, 10, 11, 12, 13, 32, 0x85, 0xA0]] = 3
        self.clear()

    def clear(self) -> None:
        self.place: dict[int, int] = {}
        self.keys = np.zeros(self.SLOTS, U)
        self.index = np.zeros(self.SLOTS, np.int64)
        self.n_words = 0
        self.n_ids = 0
        self.begin = np.zeros(1 << 16, np.int64)
        self.count = np.zeros(1 << 16, np.int64)
        self.flat = np.zeros(1 << 18, np.uint32)

    def plain(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint32)

    def cut(self, cp: np.ndarray, off: np.ndarray) -> np.ndarray:
        """Where pre-tokens start; ``cp`` holds the code points of non-empty texts that start at ``off[:-1]``."""
        kind, n = self.kind[cp], len(cp)
        first = np.zeros(n, bool)
        first[off[:-1]] = True
        last = np.zeros(n, bool)
        last[off[1:] - 1] = True
        blank = kind == 3
        change = first.copy()
        change[1:] |= kind[1:] != kind[:-1]
        joined = np.zeros(n, bool)  # a single space goes with what follows it
        joined[1:] = (cp[:-1] == 32) & ~blank[1:] & ~first[1:]
        start = change & ~joined
        # of several white-space characters before a word the last one stands alone or goes with the word
        start[:-1] |= blank[:-1] & ~blank[1:] & ~last[:-1]
        apostrophes = np.flatnonzero((cp == 39) & start & ~last)
        for i in apostrophes.tolist():
            tail = cp[i + 1 : min(i + 3, n)].tolist()
            if len(tail) == 2 and first[i + 2]:
                tail = tail[:1]
            if tail[0] in (115, 116, 109, 100):
                size = 2
            elif tail in ([114, 101], [118, 101], [108, 108]):
                size = 3
            else:
                continue
            start[i + 1] = False
            if i + size < n:
                if size == 3:
                    start[i + 2] = False
                # what follows begins a token of its own
                start[i + size] = True
        return np.flatnonzero(start)

    def learn(self, hashes: np.ndarray, words: list[str]) -> None:
        for h, word in zip(hashes.tolist(), words, strict=True):
            ids = [t.id for t in self.model.tokenize(word.encode().decode("latin-1").translate(self.letters))]
            while self.n_ids + len(ids) > len(self.flat):
                self.flat = np.r_[self.flat, np.zeros_like(self.flat)]
            if self.n_words == len(self.begin):
                self.begin = np.r_[self.begin, np.zeros_like(self.begin)]
                self.count = np.r_[self.count, np.zeros_like(self.count)]
            self.flat[self.n_ids : self.n_ids + len(ids)] = ids
            self.begin[self.n_words], self.count[self.n_words] = self.n_ids, len(ids)
            self.place[h] = self.n_words
            self.n_words += 1
            self.n_ids += len(ids)

    def many(self, cp: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of non-empty texts, all in a row, and the offsets of each text's ids."""
        starts = self.cut(cp, off)
        ends = np.r_[starts[1:], len(cp)]
        h = hash_runs(cp, starts, ends)
        slot = (h & U(self.SLOTS - 1)).astype(np.int64)
        at = self.index[slot]
        missed = np.flatnonzero(self.keys[slot] != h)
        if len(missed):
            if len(self.place) > self.MOST:
                self.clear()
                missed = np.arange(len(h))
            new, where, back = np.unique(h[missed], return_index=True, return_inverse=True)
            known = self.place
            unseen = [i for i, x in enumerate(new.tolist()) if x not in known]
            if unseen:
                source = missed[where[unseen]]
                words = [cp[a:b].tobytes().decode("utf-32-le") for a, b in zip(starts[source].tolist(), ends[source].tolist(), strict=True)]
                self.learn(new[unseen], words)
            got = np.fromiter((known[x] for x in new.tolist()), np.int64, len(new))
            at[missed] = got[back]
            self.keys[slot[missed]] = h[missed]
            self.index[slot[missed]] = at[missed]
        lengths = self.count[at]
        to = spans(lengths)
        ids = self.flat[np.arange(to[-1]) + np.repeat(self.begin[at] - to[:-1], lengths)]
        return ids, to[np.searchsorted(starts, off)]

    def texts(self, column: pa.Array):
        """For each text in turn, its ids."""
        for slab in slabs(column, 1 << 19):
            whole = slab.buf.tobytes().decode("utf-8")
            cp = np.frombuffer(whole.encode("utf-32-le"), np.uint32)
            heads = spans(((slab.buf & 0xC0) != 0x80).astype(np.int64))[slab.off]
            odd = np.zeros(len(slab), bool)
            strange = np.flatnonzero((cp >= len(self.kind)) | (self.kind[np.minimum(cp, len(self.kind) - 1)] == 0))
            odd[np.searchsorted(heads, strange, "right") - 1] = True
            odd[:] |= heads[1:] == heads[:-1]
            parts: list[np.ndarray | None] = [None] * len(slab)
            if not odd.all():
                keep = np.flatnonzero(~odd)
                sizes = (heads[1:] - heads[:-1])[keep]
                sub = spans(sizes)
                pick = cp if len(keep) == len(slab) else cp[np.arange(sub[-1]) + np.repeat(heads[keep] - sub[:-1], sizes)]
                ids, cuts = self.many(pick, sub)
                for k, i in enumerate(keep.tolist()):
                    parts[i] = ids[cuts[k] : cuts[k + 1]]
            for i, part in enumerate(parts):
                yield part if part is not None else self.plain(whole[heads[i] : heads[i + 1]])


def cut_pieces(docs: DataFrame, path: str, size: int = SIZE, end_id: int = END_ID) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of the pieces of every text: only texts of more than ``size`` tokens
    are cut, into pieces of ``size``, of which the first takes what doesn't divide."""

    def work(batches):
        enc = stash(f"encoder:{path}", lambda: Encoder(path))
        for batch in batches:
            rows: list[list] = [[], [], [], [], []]
            for doc, ids in zip(batch.column(0).to_pylist(), enc.texts(batch.column(1)), strict=True):
                raw = np.append(ids, np.uint32(end_id)).astype("<u4")
                total = len(raw)
                head = total % size or size
                cuts = [0, *range(head, total + 1, size)]
                for k in range(len(cuts) - 1):
                    a, b = cuts[k], cuts[k + 1]
                    for col, v in zip(rows, (doc, k, a, b - a, zlib.crc32(raw[a:b].tobytes())), strict=True):
                        col.append(v)
            yield pa.RecordBatch.from_arrays(
                [pa.array(c, t) for c, t in zip(rows, (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(work, PIECES)


# ---- the plan, on the driver --------------------------------------------------------------------------------------


def patterns(size: int, lengths: np.ndarray, depth: int = 3) -> np.ndarray:
    """All multisets of up to ``depth`` (1 to 3) of the lengths that sum to ``size``, as rows padded with 0."""
    has = np.zeros(size + 1, bool)
    has[lengths] = True
    out = [np.array([[size, 0, 0]])] if has[size] else []
    if depth >= 2:
        a = lengths[(2 * lengths <= size)]
        a = a[has[size - a]]
        out.append(np.stack([size - a, a, np.zeros_like(a)], 1))
    if depth >= 3:
        a = lengths[3 * lengths <= size]
        a, b = (x.ravel() for x in np.meshgrid(a, lengths, indexing="ij"))
        c = size - a - b
        ok = (a <= b) & (b <= c)
        a, b, c = a[ok], b[ok], c[ok]
        ok = has[c]
        out.append(np.stack([c[ok], b[ok], a[ok]], 1))
    return np.concatenate(out) if out else np.zeros((0, 3), np.int64)


def fit_counts(pats: np.ndarray, hist: np.ndarray, steps: int = 400) -> np.ndarray:
    """x >= 0 that makes |A x - hist| small, where A counts each length in each pattern.

    Accelerated projected gradient; a long piece left over costs a sequence more easily than a short one, so rows
    weigh more with their length."""
    if not len(pats):
        return np.zeros(0)
    size = len(hist) - 1
    weight = 0.1 + 0.9 * np.arange(size + 1) / size
    goal = hist.astype(float)
    used = (pats > 0).astype(float)
    degree = np.bincount(pats.ravel(), weights=used.ravel(), minlength=size + 1)
    weight2 = weight**2
    # each column by a step of its own: the rows it touches, by how many columns touch them
    step = 1.0 / np.maximum(1e-12, (used * (weight2 * degree)[pats]).sum(1) / np.maximum(1, used.sum(1)) * 3)
    x = np.zeros(len(pats))
    y, t = x, 1.0

    def rows(v):
        return np.bincount(pats.ravel(), weights=(used * v[:, None]).ravel(), minlength=size + 1)

    for _ in range(steps):
        left = weight2 * (rows(y) - goal)
        grad = (used * left[pats]).sum(1)
        new = np.maximum(0.0, y - step * grad)
        t2 = (1 + (1 + 4 * t * t) ** 0.5) / 2
        y = new + (t - 1) / t2 * (new - x)
        x, t = new, t2
    return x


def plan_sequences(hist: np.ndarray, depth: int = 3) -> list[tuple[tuple[int, ...], int]]:
    """Patterns and how many sequences follow each; every piece of the histogram has its place, none twice.

    ``hist[l]`` counts the pieces of length l; the last index is the size of a sequence."""
    size = len(hist) - 1
    left = hist.astype(np.int64).copy()
    plan: dict[tuple[int, ...], int] = {}
    if left[size]:
        plan[(size,)] = int(left[size])
        left[size] = 0
    lengths = np.flatnonzero(left)
    pats = patterns(size, lengths, depth) if len(lengths) else np.zeros((0, 3), np.int64)
    wanted = np.floor(fit_counts(pats, left) + 1e-6).astype(np.int64)
    for k in np.argsort(-wanted, kind="stable").tolist():
        if wanted[k] <= 0:
            break
        parts = tuple(int(v) for v in pats[k] if v)
        need = {v: parts.count(v) for v in parts}
        take = min(int(wanted[k]), *(int(left[v]) // m for v, m in need.items()))
        if take > 0:
            plan[parts] = plan.get(parts, 0) + take
            for v, m in need.items():
                left[v] -= take * m
    for parts, times in best_fit(left).items():
        plan[parts] = plan.get(parts, 0) + times
    return sorted(plan.items())


def best_fit(left: np.ndarray) -> dict[tuple[int, ...], int]:
    """Best fit on counts: the longest piece left opens sequences; each space takes the longest piece that fits it."""
    size = len(left) - 1
    left = left.copy()
    plan: dict[tuple[int, ...], int] = {}
    while True:
        there = np.flatnonzero(left)
        if not len(there):
            return plan
        parts, room = [], size
        taken = np.zeros_like(left)
        while True:
            fits = np.flatnonzero((left - taken)[: room + 1] > 0)
            if not len(fits):
                break
            v = int(fits[-1])
            parts.append(v)
            taken[v] += 1
            room -= v
        times = min(int(left[v]) // parts.count(v) for v in set(parts))
        plan[tuple(parts)] = plan.get(tuple(parts), 0) + times
        for v in set(parts):
            left[v] -= times * parts.count(v)


def slots(plan: list[tuple[tuple[int, ...], int]], size: int) -> dict[str, np.ndarray]:
    """By length and rank: where a run of ranks starts, its first sequence and its place there."""
    length, first, sequence, offset = [], [], [], []
    used = np.zeros(size + 1, np.int64)
    base = 0
    for parts, times in plan:
        at = 0
        for v in parts:
            length.append(v)
            first.append(int(used[v]))
            sequence.append(base)
            offset.append(at)
            used[v] += times
            at += v
        base += times
    cols = {"length": length, "first": first, "sequence": sequence, "offset": offset}
    cols = {k: np.array(v, np.int64) for k, v in cols.items()}
    order = np.lexsort((cols["first"], cols["length"]))
    return {k: v[order] for k, v in cols.items()}


# ---- placing --------------------------------------------------------------------------------------------------------


def place(pieces: DataFrame, size: int = SIZE, depth: int = 3, parts: int = PARTS) -> DataFrame:
    """Give every piece its sequence_id and offset; ``pieces`` is read several times, so hand in a stored table."""
    spark = pieces.sparkSession
    hist = np.zeros(size + 1, np.int64)
    for r in pieces.groupBy("length").count().collect():  # at most ``size`` rows
        hist[r["length"]] = r["count"]
    look = slots(plan_sequences(hist, depth), size)
    heads = np.searchsorted(look["length"], np.arange(size + 2))
    parts = max(parts, int(hist.max()) // PART_ROWS)
    kept = spark.sparkContext.broadcast((look, heads))

    keyed = pieces.withColumn("_part", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(parts)).cast("int"))
    here = Window.partitionBy("length", "_part")
    before = keyed.groupBy("length", "_part").agg(F.count(F.lit(1)).alias("_n"))
    before = before.withColumn("_before", F.sum("_n").over(Window.partitionBy("length").orderBy("_part")) - F.col("_n")).drop("_n")
    ranked = keyed.withColumn("_rank", F.row_number().over(here.orderBy("doc_id", "piece")).cast("long"))
    ranked = ranked.join(before, ["length", "_part"]).withColumn("_rank", F.col("_rank") - 1 + F.col("_before"))

    def work(batches):
        table_, head = kept.value
        for b in batches:
            length = b.column(b.schema.get_field_index("length")).to_numpy()
            rank = b.column(b.schema.get_field_index("_rank")).to_numpy()
            at = np.zeros(len(length), np.int64)
            for v in np.unique(length).tolist():
                mine = np.flatnonzero(length == v)
                lo, hi = head[v], head[v + 1]
                at[mine] = lo + np.searchsorted(table_["first"][lo:hi], rank[mine], "right") - 1
            seq = table_["sequence"][at] + rank - table_["first"][at]
            cols = [b.column(b.schema.get_field_index(c)) for c in ("doc_id", "piece", "start", "length", "ids_crc32")]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(seq), pa.array(table_["offset"][at])], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.select("doc_id", "piece", "start", "length", "ids_crc32", "_rank").mapInArrow(work, PIECES + ", sequence_id long, offset long")


def pack(docs: DataFrame, path: str | None = None, size: int = SIZE, depth: int = 3) -> DataFrame:
    """Pack all texts: one row per piece with the sequence it lies in and its place there."""
    return place(staged(cut_pieces(docs, path or default_tokenizer(), size), "pieces"), size, depth)


def op3_pattern_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))
