"""Each corpus operator against a brute-force form, and on the awkward inputs that its docstring defines."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from calseries.llm import chat, common, gru_lm, jaccard_join, jpeg, language, line_rules, mixing, packing, quality, textkit, toxicity
from calseries.llm.graph import components
from calseries.llm.queries import ORACLES, QUERIES

from ..conftest import SMALL, canon

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = {i: i + 32 for i in range(65, 91)}
DOCS = "doc_id long, text string, lang string, source string, n_chars long, taken string, size string, n string"


def docs(spark, texts, lang="en", source="s"):
    """Documents with nulls in every column and extra columns whose names operators use themselves."""
    rows = [(i, t, lang, source, None, "x", None, "y") for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


LONG = " ".join(f"w{i % 997}x{i % 13}" for i in range(30000))
ODD = ["", None, "one", "a b c", LONG, "Same text here, of six words.", "Same text here, of six words.", "\n\n \t", "\U0001f600 日本 émoji", "<|im_end|> \\ <| x"]


@pytest.fixture(scope="module")
def given(spark):
    return spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet")


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_oracle(spark, duck, name):
    got, want = QUERIES[name](spark, SMALL).toPandas(), duck.execute(ORACLES[name]).fetchdf()
    assert sorted(got.columns) == sorted(want.columns) and canon(got) == canon(want)


def doubling(letters, turns=12):
    """A text of two letters in which each half mirrors the other, the worst case for polynomial hashes."""
    x = letters[0]
    for _ in range(turns):
        x += x.translate(str.maketrans(letters, letters[::-1]))
    return x


PAIR = doubling("ab"), doubling("ba")


def test_runs_of_mirrored_texts_differ(spark):
    one, two = PAIR
    raw = np.frombuffer((one + two + one).encode(), np.uint8)
    for values in (raw, raw.astype(np.uint32)):
        n = len(one)
        h = textkit.hash_runs(values, np.array([0, n, 2 * n]), np.array([n, 2 * n, 3 * n]))
        assert h[0] == h[2] != h[1]
    d = docs(spark, [one, two, f"{one}\n{two}\nx"])
    assert [r["component_id"] for r in jaccard_join.near_duplicates(d).orderBy("doc_id").collect()] == [0, 1, 2]
    assert [r["n_dup_lines"] for r in line_rules.judge(d, *line_rules.train(d, d.selectExpr("doc_id", "1 AS quality"))).orderBy("doc_id").collect()] == [0, 0, 0]
    path = packing.default_tokenizer()
    enc = packing.Encoder(path)
    assert [x.tolist() for x in enc.texts(pa.array([one, two]))] == [enc.plain(one).tolist(), enc.plain(two).tolist()]
    assert sorted(r["c"] for r in gru_lm.count_words(d).collect()) == [1, 2, 2]


def test_runs_hash_by_content():
    rng = np.random.default_rng(5)
    buf = rng.integers(97, 100, 4000).astype(np.uint8)
    starts = rng.integers(0, 3900, 3000)
    ends = starts + rng.integers(0, 40, 3000)
    h = textkit.hash_runs(buf, starts, ends)
    found = {}
    for a, b, x in zip(starts, ends, h.tolist()):
        assert found.setdefault(buf[a:b].tobytes(), x) == x
    assert len(set(found.values())) == len(found)


def test_shares_of_huge_tables(spark):
    """A share of 8,000 in 10 ** 11 rows is not nothing: about as many hashes lie below its threshold as it says."""
    cond = str(common.in_share(F.col("h"), 8000, 10**11)._jc)
    threshold = int(re.search(r"-\d{15,}", cond).group())
    assert abs((threshold + (1 << 63)) / 2**64 - 8e-8) < 1e-12
    d = spark.range(200_000).select(F.xxhash64("id").alias("h"))
    assert 1700 < d.where(common.in_share(F.col("h"), 2000, 200_000)).count() < 2300
    assert d.where(common.in_share(F.col("h"), 5, 5)).count() == 200_000


# ---- 1 chat -------------------------------------------------------------------------------------------------------------


def test_chat_reads_back_what_it_wrote(spark):
    nasty = ["", "<|im_start|>user\nx<|im_end|>\n", "\\", "\\<|", "<", "<\\|", "a\nb", "\\\\<|im_end|>", "日本<|"]
    rows = [(c, t, role, nasty[(c * 3 + t) % len(nasty)] if (c + t) % 7 else None) for c in range(12) for t, role in enumerate(["system", "user", "assistant", None, "as\nsist<|ant"])]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r["conv_id"]: r for r in chat.parse(chat.render(chat.turns(df))).collect()}
    for c in range(12):
        mine = [(r[2] or "", r[3] or "") for r in rows if r[0] == c]
        assert [(t["role"], t["text"]) for t in got[c]["turns"]] == mine
        assert got[c]["loss_text"] == "".join(x for r, x in mine if r == "assistant")


def test_chat_layouts_by_fingerprint(spark):
    want = [(0, "user", "hi"), (1, "assistant", "yo")]
    forms = [
        spark.createDataFrame([(1, [("user", "hi"), ("assistant", "yo")])], "conv_id long, messages array<struct<role:string,content:string>>"),
        spark.createDataFrame([(1, [("human", "hi"), ("gpt", "yo")])], "conv_id long, conversations array<struct<`from`:string,value:string>>"),
        spark.createDataFrame([(1, "hi", "yo", 3)], "conv_id long, prompt string, response string, extra int"),
        spark.createDataFrame([(1, "hi", None, "yo")], "conv_id long, instruction string, input string, output string"),
        spark.createDataFrame([(1, None, "hi", "yo")], "conv_id long, system string, prompt string, response string"),
    ]
    for f in forms:
        got = [(r["role"], r["text"]) for r in chat.turns(f).orderBy("turn").collect()]
        assert got == [w[1:] for w in want]
    assert len({chat.fingerprint(f.schema) for f in forms}) == len(forms)
    with pytest.raises(ValueError):
        chat.turns(spark.range(1))


def test_chat_of_odd_rows(spark):
    """A null conversation is one of its own, equal turns keep both texts, and long and repeated rows stay whole."""
    rows = [(None, 0, "user", "a"), (None, 1, "assistant", None), (1, 0, "user", "b"), (1, 0, "user", "b"), (2, 0, "assistant", LONG), (3, None, None, "")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r["conv_id"]: [(t["role"], t["text"]) for t in r["turns"]] for r in chat.parse(chat.render(chat.turns(df))).collect()}
    assert got == {None: [("user", "a"), ("assistant", "")], 1: [("user", "b")] * 2, 2: [("assistant", LONG)], 3: [("", "")]}


def test_chat_of_nothing(spark):
    empty = spark.createDataFrame([], "conv_id long, turn long, role string, text string")
    assert chat.digest(chat.render(chat.turns(empty))).count() == 0


# ---- 2 and 9 classifiers ---------------------------------------------------------------------------------------------------


def test_machine_learns_a_pair(spark):
    """Neither term alone is bad, both together are: weights alone can't say that."""
    rng = random.Random(3)
    texts, y = [], []
    for _ in range(1600):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        words = [f"filler{rng.randrange(60)}" for _ in range(12)] + ["group"] * a + ["insult"] * b
        rng.shuffle(words)
        texts.append(" ".join(words))
        y.append(int(a and b))
    slab = next(iter(packing.slabs(pa.array(texts), 1 << 30, 1000)))
    bucket, owner = toxicity.terms(slab)
    n = len(slab)
    off = np.searchsorted(owner, np.arange(n + 1))
    model = toxicity.learn(np.array(y[:n]), bucket, off)
    score = toxicity.score_batch(pa.array(["group of people", "insult to music", "insult the group", "", None]), model)
    assert score[2] > 0.7 > max(score[0], score[1]) and ((score >= 0) & (score <= 1)).all()


def test_toxic_documents_are_found(spark):
    got = toxicity.op2_factorization_machine(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id").toPandas()
    clean = got[got.toxic == 0]
    assert clean.predicted.mean() < 0.02
    assert got[(got.toxic == 1)].predicted.mean() > 0.75


def test_quality_on_rows_left_out(spark):
    got = quality.op9_random_indexing(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id").where("held_out").toPandas()
    assert (got.predicted == got.quality).mean() > 0.9 and got.score.between(0, 1).all()


@pytest.mark.parametrize("train,score", [(toxicity.train, toxicity.score), (quality.train, quality.score)])
def test_classifiers_on_odd_rows(spark, train, score):
    d = docs(spark, ODD)
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = [r["score"] for r in score(d, train(d, none)).collect()]
    assert len(got) == len(ODD) and all(0 <= x <= 1 for x in got)
    some = spark.createDataFrame([(2, 1, 0), (3, 0, 1), (5, 1, 0), (6, None, None), (None, 1, 1), (4, 0, 1), (7, 1, 0)], "doc_id long, quality int, toxic int")
    rows = score(d, train(d, some)).collect()
    assert len(rows) == len(ODD) and {r["doc_id"]: r["score"] for r in rows}[5] == {r["doc_id"]: r["score"] for r in rows}[6]
    assert score(d.limit(0), train(d, some)).count() == 0


# ---- 3 packing --------------------------------------------------------------------------------------------------------------


def test_packing_is_whole_and_gapless(spark, given):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(packing.default_tokenizer())
    t.encode_special_tokens = True
    d = given[0].select("doc_id", "text").unionByName(docs(spark, ODD).select((F.col("doc_id") + 100000).alias("doc_id"), "text"))
    texts = {r["doc_id"]: r["text"] for r in d.collect()}
    got = packing.pack(d).toPandas()
    assert set(got.doc_id) == set(texts)
    for doc, part in got.sort_values(["doc_id", "piece"]).groupby("doc_id"):
        ids = np.array([*t.encode(texts[doc] or "", add_special_tokens=False).ids, 2], "<u4")
        assert part.length.sum() == len(ids) and list(part.piece) == list(range(len(part)))
        assert (part.length.iloc[1:] == 1024).all() and (len(part) > 1 or len(ids) <= 1024)
        assert [zlib.crc32(ids[a : a + n].tobytes()) for a, n in zip(part.start, part.length)] == list(part.ids_crc32)
    for _, s in got.sort_values(["sequence_id", "offset"]).groupby("sequence_id"):
        assert list(s.offset) == [0, *np.cumsum(s.length)[:-1]] and s.length.sum() <= 1024
    assert got.sequence_id.nunique() <= math.ceil(got.length.sum() / 1024) * 1.02 + 1
    assert packing.pack(d.limit(0)).count() == 0


def test_pretokens_equal_the_librarys():
    enc = packing.Encoder(packing.default_tokenizer())
    rng = random.Random(5)
    bits = ["'s", "'re", "'", " ", "  ", "\n", "\t", "it", "É", "12", "½", "!", "...", "<|endoftext|>", "’", "日", " ", "ll", "'ll", "d"]
    texts = ["".join(rng.choice(bits) for _ in range(rng.randrange(12))) for _ in range(3000)]
    want = [e.ids for e in enc.tokenizer.encode_batch(texts, add_special_tokens=False)]
    assert [x.tolist() for x in enc.texts(pa.array(texts))] == want


def test_plan_places_every_piece_once():
    rng = np.random.default_rng(2)
    for _ in range(5):
        hist = np.zeros(1025, np.int64)
        np.add.at(hist, rng.integers(1, 1025, 4000), 1)
        plan = packing.plan_sequences(hist)
        used = np.zeros(1025, np.int64)
        for parts, times in plan:
            assert sum(parts) <= 1024
            for v in parts:
                used[v] += times
        assert (used == hist).all()
        assert sum(t for _, t in plan) <= math.ceil((hist * np.arange(1025)).sum() / 1024) * 1.03


# ---- 4 mixing ---------------------------------------------------------------------------------------------------------------


def water(sizes, weights):
    """Targets by repeated resharing."""
    total, target, open_ = 1.5 * sum(sizes), [0.0] * len(sizes), set(range(len(sizes)))
    left = total
    while open_ and left > 1e-9:
        w = sum(weights[i] for i in open_)
        gift = {i: left * weights[i] / w for i in open_}
        left = 0.0
        for i in list(open_):
            target[i] += gift[i]
            if target[i] >= 2 * sizes[i]:
                left += target[i] - 2 * sizes[i]
                target[i] = 2.0 * sizes[i]
                open_.discard(i)
    return target


def test_targets_equal_resharing(spark):
    rng = random.Random(1)
    for _ in range(6):
        names = [*sorted(f"s{i}" for i in range(rng.randrange(1, 8))), None]
        sizes = [rng.choice([0, 5, 1000, 40000]) + rng.randrange(50) for _ in names]
        df = spark.createDataFrame(list(zip(names, sizes)), "source string, source_size long")
        got = {r["source"]: r["target"] for r in mixing.targets(df).collect()}
        want = water(sizes, [(5, 2, 1)[i % 3] for i in range(len(names))])
        assert all(abs(got[n] - w) < 1e-6 * (1 + w) for n, w in zip(names, want))


def test_mix_takes_whole_documents_near_the_target(spark, given):
    d = given[0]
    m = mixing.mix(d)
    assert m.schema == d.schema
    again = sorted(r["doc_id"] for r in mixing.mix(d).select("doc_id").collect())
    assert sorted(r["doc_id"] for r in m.select("doc_id").collect()) == again
    drawn = {(r["doc_id"]): (r["taken"], r["size"]) for r in mixing.draw(d, cut="document").collect()}
    times = collections.Counter(r for r in again)
    assert all(times[k] * s == t for k, (t, s) in drawn.items() if s)


def test_mix_on_odd_rows(spark):
    d = docs(spark, ODD, source=None).unionAll(docs(spark, ["a b c d"] * 5, source="t"))
    got = mixing.draw(d).collect()
    assert len(got) == len(ODD) + 5 and all(0 <= r["taken"] <= 2 * r["size"] for r in got)
    for s in (None, "t"):
        mine = [r for r in got if r["source"] == s]
        assert abs(sum(r["taken"] for r in mine) - mine[0]["target"]) <= 1
    assert mixing.draw(d.limit(0)).count() == 0 and mixing.mix(d).columns == d.columns


def test_mix_of_repeated_rows_and_clashing_names(spark):
    d = spark.range(1000).selectExpr("7L AS doc_id", "'a b c d' AS text", "CAST(NULL AS STRING) AS source", "1 AS mix_times", "2 AS mix_last", "3 AS mix_copy")
    d = d.unionByName(spark.range(50).selectExpr("id AS doc_id", "'e f g' AS text", "'t' AS source", "1 AS mix_times", "2 AS mix_last", "3 AS mix_copy"))
    goal = {r["source"]: r["target"] for r in mixing.draw(d).select("source", "target").distinct().collect()}
    got = mixing.mix(d)
    assert got.columns == d.columns
    for source, size in ((None, 4), ("t", 3)):
        taken = got.where(F.col("source").eqNullSafe(F.lit(source))).count() * size
        assert abs(taken - goal[source]) <= size


# ---- 5 line rules -----------------------------------------------------------------------------------------------------------


def base_counts(t):
    t = t or ""
    w, seen, dup = WORD.findall(t), set(), 0
    for line in t.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    c = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    cover = {k for i in range(len(w) - 4) if c[tuple(w[i : i + 5])] > 1 for k in range(i, i + 5)}
    return len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), dup, len(cover)


def test_line_rules_base_counts(spark, given):
    d = given[0].select("doc_id", "text").unionByName(docs(spark, [*ODD, "x y\nx y\n\n\nx y", "a b c d e a b c d e\r\n"]).select((F.col("doc_id") + 100000).alias("doc_id"), "text"))
    texts = {r["doc_id"]: r["text"] for r in d.collect()}
    got = line_rules.judge(d, *line_rules.train(*given)).collect()
    for r in got:
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == base_counts(texts[r["doc_id"]])
        assert r["base_failed"] == (r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"]) and not (r["base_failed"] and r["kept"])
    labels = {r["doc_id"]: r["quality"] for r in given[1].collect()}
    good = [r["kept"] for r in got if labels.get(r["doc_id"]) == 1 and not r["base_failed"]]
    assert sum(good) / len(good) > 0.97
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert line_rules.judge(d.limit(0), *line_rules.train(d, none)).count() == 0


def test_viterbi_is_the_best_path():
    rng = np.random.default_rng(0)
    for _ in range(30):
        sizes = rng.integers(1, 7, 4)
        text = np.repeat(np.arange(4), sizes)
        emit, stick = rng.normal(size=len(text)), rng.normal(size=(2, 2))
        got = line_rules.viterbi(emit, stick, text)
        for k in range(4):
            e, path = emit[text == k], got[text == k]
            worth = lambda p, e=e: sum(e[i] * v for i, v in enumerate(p)) + sum(stick[a, b] for a, b in zip(p, p[1:]))
            assert abs(worth(path) - max(worth(p) for p in itertools.product((0, 1), repeat=len(e)))) < 1e-9


def test_field_is_at_the_top_of_its_likelihood():
    """The fitted weights against the likelihood summed over all labellings: no single change of a weight raises it."""
    rng = np.random.default_rng(7)
    text = np.repeat(np.arange(12), rng.integers(1, 6, 12))
    x = (rng.random((len(text), 4)) < 0.5).astype(float)
    y = ((x[:, 0] + 0.7 * rng.normal(size=len(text))) > 0.5).astype(np.int64)
    decay = 1e-2

    def objective(w, stick):
        total = 0.0
        for t in np.unique(text):
            e, mine = x[text == t] @ w, y[text == t]

            def path(labels):
                return sum(e[i] * v for i, v in enumerate(labels)) + sum(stick[a, b] for a, b in itertools.pairwise(labels))

            total += path(mine) - np.logaddexp.reduce([path(p) for p in itertools.product((0, 1), repeat=len(mine))])
        return total / len(text) - decay / 2 * (np.sum(w**2) + np.sum(stick**2))

    w, stick = line_rules.fit(x, y, text, rounds=3000, rate=0.02, decay=decay)
    top = objective(w, stick)
    for i in range(4):
        for step in (-0.05, 0.05):
            moved = w.copy()
            moved[i] += step
            assert objective(moved, stick) < top
    for i, j in itertools.product((0, 1), repeat=2):
        for step in (-0.05, 0.05):
            moved = stick.copy()
            moved[i, j] += step
            assert objective(w, moved) < top


def test_field_gradient_reaches_the_likelihood():
    rng = np.random.default_rng(1)
    x = np.c_[np.ones(400), rng.random(400) < 0.5].astype(float)
    y = (x[:, 1] > 0).astype(int)
    w, stick = line_rules.fit(x, y, np.repeat(np.arange(40), 10))
    assert (line_rules.viterbi(x @ w, stick, np.repeat(np.arange(40), 10)) == y).mean() > 0.97


# ---- 6 JPEG -----------------------------------------------------------------------------------------------------------------


def slow_decode(data):
    """One bit at a time: the luminance DC samples of a single-component stream with restart markers."""
    s = jpeg.parse(data)[0]
    dc, ac = ({(n, c): k for k, (c, n) in jpeg.codes_of(*s.huff[t]).items()} for t in (0x00, 0x10))
    body, out = data[s.begin : s.end], []
    parts = re.split(rb"\xff[\xd0-\xd7]", body)
    for part in parts:
        bits = "".join(f"{b:08b}" for b in part.replace(b"\xff\x00", b"\xff"))
        at, pred = 0, 0

        def read(table):
            nonlocal at
            n = 1
            while (n, int(bits[at : at + n], 2)) not in table:
                n += 1
            v = table[(n, int(bits[at : at + n], 2))]
            at += n
            return v

        for _ in range(s.every):
            k = read(dc)
            v = int(bits[at : at + k], 2) if k else 0
            at += k
            pred += v if k == 0 or v >= 1 << (k - 1) else v - (1 << k) + 1
            i = 1
            while i < 64:
                sym = read(ac)
                if sym == 0:
                    break
                i += (sym >> 4) + 1
                at += sym & 15
            out.append(max(0, min(255, 128 + pred)))
    return bytes(out)


def test_jpeg_round_trip_and_plain_decoder():
    rng = random.Random(9)
    texts = ["", None, "x", "é" * 300, "abc def " * 200, "".join(chr(rng.randrange(32, 900)) for _ in range(3000)), "ÿ" * 600]
    for t, (n, payload, data, planes) in zip(texts, jpeg.media(pa.array(texts))):
        raw = (t or "").encode()
        want = raw + b"\xff" * ((-len(raw)) % 576 if raw else 576)
        assert n == len(raw) and payload == want == slow_decode(data)
        assert jpeg.features(data, planes).startswith("192x")


def colour_stream(h=2, v=2, width=40, height=24, every=0):
    """A three-component stream with AC coefficients, and its luminance DC plane."""
    rng = random.Random(h * 10 + v + every)
    dc = jpeg.table_of({k: 4 for k in range(12)})
    ac = jpeg.table_of({0x00: 2, 0xF0: 5, 0x01: 3, 0x12: 4, 0x35: 5, 0xA1: 6})
    dcc, acc = jpeg.codes_of(*dc), jpeg.codes_of(*ac)
    q = 5
    ux, uy = -(-width // (8 * h)), -(-height // (8 * v))
    plane = np.zeros((uy * v, ux * h), int)
    bits, body, pred, units, mark = "", b"", [0, 0, 0], 0, 0

    def flush():
        nonlocal bits
        bits += "1" * (-len(bits) % 8)
        out = bytes(int(bits[i : i + 8], 2) for i in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
        bits = ""
        return out

    for y in range(uy):
        for x in range(ux):
            if every and units and units % every == 0:
                body += flush() + bytes([0xFF, 0xD0 + mark % 8])
                mark, pred = mark + 1, [0, 0, 0]
            for c, (ch, cv) in enumerate([(h, v), (1, 1), (1, 1)]):
                for b in range(ch * cv):
                    val = rng.randrange(-180, 180)
                    d = val - pred[c]
                    pred[c] = val
                    k = abs(d).bit_length()
                    bits += f"{dcc[k][0]:0{dcc[k][1]}b}" + (f"{d if d > 0 else d + (1 << k) - 1:0{k}b}" if k else "")
                    left = 63
                    while left > 20 and rng.random() < 0.7:
                        sym = rng.choice([0x01, 0x12, 0x35, 0xA1, 0xF0])
                        bits += f"{acc[sym][0]:0{acc[sym][1]}b}" + "".join(rng.choice("01") for _ in range(sym & 15))
                        left -= (sym >> 4) + 1
                    bits += f"{acc[0][0]:0{acc[0][1]}b}"
                    if c == 0:
                        plane[y * v + b // h, x * h + b % h] = val
            units += 1
    body += flush()
    seg = jpeg._segment
    frame = bytes([8]) + height.to_bytes(2, "big") + width.to_bytes(2, "big") + bytes([3, 1, h << 4 | v, 0, 2, 0x11, 0, 3, 0x11, 0])
    data = b"\xff\xd8" + seg(0xE0, b"JFIF\0") + seg(0xDB, bytes([0]) + bytes([q] * 64)) + seg(0xC0, frame)
    data += seg(0xC4, b"\x00" + dc[0] + dc[1]) + seg(0xC4, b"\x10" + ac[0] + ac[1]) + (seg(0xDD, every.to_bytes(2, "big")) if every else b"")
    data += seg(0xDA, bytes([3, 1, 0, 2, 0, 3, 0, 0, 63, 0])) + body + b"\xff\xd9"
    want = np.clip((plane * q + 4 + 1024) >> 3, 0, 255)
    return data, want[: -(-height // 8), : -(-width // 8)]


@pytest.mark.parametrize("h,v,every", [(1, 1, 0), (2, 1, 0), (2, 2, 0), (2, 2, 2), (1, 1, 3)])
def test_jpeg_reads_colour_streams(h, v, every):
    data, want = colour_stream(h, v, every=every)
    assert (jpeg.dc_planes([data])[0][0] == want).all()


def split_stream(h, v, order, width=40, height=24, every=0):
    """Three components in scans of their own, each with tables of its own, and the luminance's DC plane."""
    rng = random.Random(h * 10 + v + every)
    seg, scans, want = jpeg._segment, {}, None
    for c, (ch, cv) in enumerate([(h, v), (1, 1), (1, 1)]):
        size = list(range(12))
        rng.shuffle(size)
        counts, symbols = jpeg.table_of({k: 4 for k in size})
        code = jpeg.codes_of(counts, symbols)
        nx, ny = -(-(-(-width * ch // h)) // 8), -(-(-(-height * cv // v)) // 8)
        plane, body, bits, pred, mark = np.array([[rng.randrange(-180, 180) for _ in range(nx)] for _ in range(ny)]), b"", "", 0, 0
        for n, val in enumerate([*plane.ravel().tolist(), None]):
            if val is None or every and n and n % every == 0:
                bits += "1" * (-len(bits) % 8)
                body += bytes(int(bits[i : i + 8], 2) for i in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
                if val is None:
                    break
                body, bits, pred, mark = body + bytes([0xFF, 0xD0 + mark % 8]), "", 0, mark + 1
            d, pred = val - pred, val
            k = abs(d).bit_length()
            bits += f"{code[k][0]:0{code[k][1]}b}" + (f"{d if d > 0 else d + (1 << k) - 1:0{k}b}" if k else "") + "0"
        scans[c] = seg(0xC4, b"\x00" + counts + symbols) + seg(0xC4, b"\x10" + bytes([1] + [0] * 15) + b"\x00") + seg(0xDA, bytes([1, c + 1, 0, 0, 63, 0])) + body
        want = plane if c == 0 else want
    frame = bytes([8]) + height.to_bytes(2, "big") + width.to_bytes(2, "big") + bytes([3, 1, h << 4 | v, 0, 2, 0x11, 0, 3, 0x11, 0])
    data = b"\xff\xd8" + seg(0xDB, bytes([0]) + bytes([5] * 64)) + seg(0xC0, frame) + (seg(0xDD, every.to_bytes(2, "big")) if every else b"")
    return data + b"".join(scans[c] for c in order) + b"\xff\xd9", np.clip((want * 5 + 4 + 1024) >> 3, 0, 255)


@pytest.mark.parametrize("h,v,every", [(1, 1, 0), (2, 1, 0), (2, 2, 0), (2, 2, 2), (1, 1, 3)])
@pytest.mark.parametrize("order", [(0, 1, 2), (1, 0, 2), (2, 1, 0)])
def test_jpeg_reads_scans_of_single_components(h, v, every, order):
    data, want = split_stream(h, v, order, every=every)
    other, beside = colour_stream(h, v, every=every)
    for got, plane in zip(jpeg.dc_planes([data, other]), (want, beside)):
        assert got[0].shape == plane.shape and (got[0] == plane).all()
    odd, want = split_stream(h, v, order, 37, 9, every)
    assert jpeg.parse(odd)[0].width == 37 and (jpeg.dc_planes([odd + data])[0][0] == want).all()


def test_jpeg_without_a_luminance_scan():
    with pytest.raises(ValueError):
        jpeg.parse(split_stream(2, 2, (1, 2))[0])


def test_jpeg_column(spark):
    data, want = colour_stream()
    rows = spark.createDataFrame([(1, bytearray(data)), (2, bytearray(b"no picture")), (3, None)], "width long, data binary")
    got = {r["width"]: r for r in jpeg.thumbnails(rows).collect()}
    assert got[1]["_width"] == 40 and bytes(got[1]["_thumbnail"]) == want.astype(np.uint8).tobytes() and got[2]["_hash"] is None and got[3]["_hash"] is None
    named = jpeg.thumbnails(rows.withColumnRenamed("width", "_hash"))
    assert len(set(named.columns)) == 5 and sorted(r["_hash"] for r in named.collect()) == [1, 2, 3] and jpeg.thumbnails(rows.limit(0)).count() == 0


def test_jpeg_query_values(spark):
    got = jpeg.digests(docs(spark, ODD)).toPandas().sort_values("doc_id")
    for t, r in zip(ODD, got.itertuples()):
        raw = (t or "").encode()
        want = raw + b"\xff" * ((-len(raw)) % 576 if raw else 576)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(want), hashlib.sha256(want).hexdigest(), zlib.crc32(want[-32:]))
    assert got.media_sha256.iloc[5] == got.media_sha256.iloc[6] and jpeg.digests(docs(spark, ODD).limit(0)).count() == 0


# ---- 7 Jaccard ----------------------------------------------------------------------------------------------------------------


def brute_components(texts, k=4, percent=85):
    sets = {}
    for i, t in texts.items():
        w = WORD.findall((t or "").translate(LOW))
        sets[i] = frozenset(tuple(w[j : j + k]) for j in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)]) if w else frozenset()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in itertools.combinations(sorted(i for i in sets if sets[i]), 2):
        o = len(sets[a] & sets[b])
        if o and 100 * o >= percent * (len(sets[a]) + len(sets[b]) - o):
            ra, rb = find(a), find(b)
            root[max(ra, rb)] = min(ra, rb)
    return {i: (len(s), find(i)) for i, s in sets.items()}


@pytest.mark.parametrize("k,percent", [(4, 85), (5, 80)])
def test_jaccard_equals_all_pairs(spark, k, percent):
    rng = random.Random(k)
    texts = list(ODD)
    for size in (5, 7, 9, 10, 12, 16, 17, 19, 22, 24, 28, 40, 90):
        for _ in range(3):
            w = [f"v{rng.randrange(10**6)}" for _ in range(size)]
            for _ in range(6):
                x = list(w)
                for _ in range(rng.randrange(4)):
                    op, at = rng.randrange(3), rng.choice([0, 0, len(x) - 1, rng.randrange(len(x))])
                    x = x[:at] + ([] if op == 0 else [f"n{rng.randrange(50)}"]) + x[at + (op != 2) :] or ["z"]
                texts.append(" ".join(x).upper() if rng.random() < 0.2 else "  ".join(x))
    passage = [f"p{i}" for i in range(30)]
    texts += [" ".join([*passage, *[f"q{rng.randrange(10**6)}" for _ in range(rng.randrange(3, 40))]]) for _ in range(60)]
    want = brute_components(dict(enumerate(texts)), k, percent)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.near_duplicates(docs(spark, texts), k, percent).collect()}
    assert got == want


def test_jaccard_sets_inside_larger_ones(spark):
    """All that the larger text has beyond the smaller one is rarer than what they share, at exactly 80 of 100."""
    texts = []
    for i in range(12):
        w = [f"g{i}x{j}" for j in range(84)]
        texts += [" ".join(w), " ".join([*w, *[f"r{i}x{j}" for j in range(20)]])]
    want = brute_components(dict(enumerate(texts)), 5, 80)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.near_duplicates(docs(spark, texts), 5, 80).collect()}
    assert got == want and len({c for _, c in got.values()}) == 12


def test_jaccard_boundary_and_subsets():
    assert all(jaccard_join.needed(s, t) * 100 >= 85 * (s + t - jaccard_join.needed(s, t)) > 0 for s in range(1, 40) for t in range(s, 40))
    assert all(100 * (jaccard_join.needed(s, t) - 1) < 85 * (s + t - jaccard_join.needed(s, t) + 1) for s in range(1, 40) for t in range(1, 40))
    assert jaccard_join.choose_boundary({}) >= 1 and 5 <= jaccard_join.choose_boundary({s: 1000 for s in range(1, 60)}) <= 20


def test_jaccard_blocks(spark, monkeypatch):
    """A cluster of many blocks: links across blocks count, and rows with a null id or a shared id are defined."""
    monkeypatch.setattr(jaccard_join, "BLOCK", 1500)
    rng = random.Random(11)
    w = [f"b{i}" for i in range(60)]
    texts = []
    for _ in range(40):
        x = list(w)
        for _ in range(rng.randrange(5)):
            x[rng.randrange(60)] = f"m{rng.randrange(9)}"
        texts.append(" ".join(x))
    want = brute_components(dict(enumerate(texts)))
    d = docs(spark, texts)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.near_duplicates(d).collect()}
    assert got == want
    more = d.select("doc_id", "text").unionAll(spark.createDataFrame([(None, texts[0]), (None, "all alone in the world"), (0, texts[0])], "doc_id long, text string"))
    rows = jaccard_join.near_duplicates(more).where("doc_id IS NULL").collect()
    assert sorted(str(r["component_id"]) for r in rows) == sorted(["None", str(want[0][1])])
    assert jaccard_join.near_duplicates(d.limit(0)).count() == 0


def test_jaccard_unlike_texts_leave_large_clusters(spark, monkeypatch):
    """Texts chained by shared passages don't travel to every block of one cluster; no link is lost on the way."""
    monkeypatch.setattr(jaccard_join, "BLOCK", 4000)
    seen, kept = [], jaccard_join.verified
    monkeypatch.setattr(jaccard_join, "verified", lambda docs, members, *a: seen.append(members.groupBy("cluster").count().toPandas()["count"]) or kept(docs, members, *a))
    passage = lambda kind, i: [f"{kind}{i}w{j}" for j in range(20)]
    texts = [" ".join([*passage("a", i), *passage("b", j), *passage("c", (i + j) % 7)]) for i in range(7) for j in range(7)]
    texts += [x.replace("w19", "z", 1) for x in texts[::4]]
    want = brute_components(dict(enumerate(texts)))
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.near_duplicates(docs(spark, texts)).collect()} == want
    assert max(seen[0]) < len(texts) / 4 and len(set(c for _, c in want.values())) == 49


@pytest.mark.parametrize("percent", [85, 80])
def test_jaccard_equal_parts_are_enough(spark, percent):
    """Linked sets share a posting, whatever their sizes; small sets and those with few full parts too."""
    rng = random.Random(percent)
    texts = []
    for size in [*range(1, 60), 90, 150, 151, 180, 400]:
        w = [f"u{rng.randrange(10**9)}" for _ in range(size + 3)]
        texts += [" ".join(w), " ".join(w[: max(4, -(-size * percent // 100) + 3)]), " ".join([*w[: size + 2], "z"]), " ".join(["y", *w[1:]])]
    d = docs(spark, texts)
    slab = next(textkit.slabs(pa.array(texts), most=10**6))
    h, owner = jaccard_join.sets(slab)
    sets = [h[owner == i] for i in range(len(texts))]
    f1 = [int(np.add.reduce(textkit.mix(x + np.uint64(1)), dtype=np.uint64).view(np.int64)) for x in sets]
    members = spark.createDataFrame([(i, 0) for i in range(len(texts))], "rep long, x int")
    posted = collections.defaultdict(set)
    for r in jaccard_join.signatures(d, members, np.zeros(jaccard_join.SKETCH, np.uint8), percent=percent).collect():
        posted[r["f1"]].add((r["key"], r["c"]))
    a, b = jaccard_join.links(sets, np.zeros(len(sets), int), percent)
    assert len(a) > 100
    for i, j in zip(a.tolist(), b.tolist(), strict=True):
        assert posted[f1[i]] & posted[f1[j]]


def test_jaccard_repeated_ids(spark):
    """Different texts under one id are documents of their own, in whatever order they come."""
    base = " ".join(f"a{i}" for i in range(40))
    alike = base.replace("a39", "z")
    rows = [(5, "quite another text with words of its own here"), (5, base), (9, alike)]
    for order in ((0, 1, 2), (1, 0, 2), (2, 1, 0)):
        d = spark.createDataFrame([rows[i] for i in order], "doc_id long, text string")
        got = {(r["doc_id"], r["n_shingles"]): r["component_id"] for r in jaccard_join.near_duplicates(d).collect()}
        assert got == {(5, 6): 5, (5, 37): 5, (9, 37): 5}
        kept = sorted((r["doc_id"], r["text"]) for r in jaccard_join.keep_one(d.unionAll(d)).collect())
        assert kept == sorted(rows[:2])


def test_jaccard_hot_class(spark, monkeypatch):
    """A class of a third of all rows is told its component by broadcast."""
    from calseries.llm import graph

    monkeypatch.setattr(graph, "HOT", 5)
    monkeypatch.setattr(jaccard_join, "HOT", 5)
    texts = ["the same words in the same order again"] * 30 + [f"w{i} x{i} y{i} z{i} q{i}" for i in range(40)]
    want = brute_components(dict(enumerate(texts)))
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.near_duplicates(docs(spark, texts)).collect()} == want


def test_keep_one_keeps_columns(spark):
    d = docs(spark, ["a b c d e f g h", "a b c d e f g h", "other words stand in this one", None])
    got = jaccard_join.keep_one(d)
    assert got.schema == d.schema and sorted(r["doc_id"] for r in got.collect()) == [0, 2, 3]


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 60)] + [(100, 90), (90, 95), (7, 7)]
    got = {r["node"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(1, 61)} | {95: 90, 100: 90}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_components_around_hot_nodes(spark):
    """Two hubs with most of the edges, chains whose nodes are all cold, and a link between the hubs' leaves."""
    hubs = [(5, i) for i in range(1000, 4000)] + [(9, i) for i in range(5000, 7000)] + [(3999, 5000)]
    chain = [(i, i + 1) for i in range(10000, 10300)]
    got = {r["node"]: r["root"] for r in components(spark.createDataFrame(hubs + chain, "a long, b long")).collect()}
    assert got == dict.fromkeys([9, *range(1000, 4000), *range(5000, 7000)], 5) | dict.fromkeys(range(10001, 10301), 10000)


# ---- 8 languages --------------------------------------------------------------------------------------------------------------


def test_language_on_rows_left_out(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = language.op8_mixture_language(spark, "/root/testdata/sf0.01").join(d.select("doc_id", "lang"), "doc_id").where("held_out").toPandas()
    assert (got.lang_pred == got.lang).mean() > 0.97 and got.score.between(0, 1).all()


def test_language_of_long_repeated_and_no_rows(spark):
    names, logp = language.learn(docs(spark, ["the and with that"] * 3, "en").unionAll(docs(spark, ["und der die das"], "de")))
    d = docs(spark, ["the with " * 20000, "und das", "und das"])
    assert [r["lang_pred"] for r in language.identify(d, names, logp).orderBy("doc_id").collect()] == ["en", "de", "de"]
    assert language.identify(d.limit(0), names, logp).count() == 0
    few = docs(spark, ["the and with that"] * 400, "en").unionAll(docs(spark, ["und der die das"], "de"))
    assert language.learn(few)[0] == ["de", "en"]


def test_language_mixture_and_odd_rows(spark):
    train = docs(spark, ["the and with that this have from they will would there their"] * 9, "en").unionAll(docs(spark, ["und der die das nicht eine auch sich auf mit werden durch"] * 9, "de"))
    names, logp = language.learn(train)
    assert names == ["de", "en"]
    mixed = "the and with that this have from they will would there their " * 6 + "und der die das nicht eine auch sich auf mit werden durch " * 4
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language.identify(docs(spark, [mixed, "und das auch", None, "", "123 !!", "日本", "½"]), names, logp).collect()}
    sets = {r["doc_id"]: [x["lang"] for x in r["languages"]] for r in language.identify(docs(spark, [mixed, "und das auch", None]), names, logp).collect()}
    assert sets == {0: ["en", "de"], 1: ["de"], 2: []}
    assert got[0][0] == "en" and 0.5 < got[0][1] < 0.75 and got[1][0] == "de"
    assert [got[i] for i in (2, 3, 4, 6)] == [("und", 0.0)] * 4 and got[5][0] in names
    none, table_ = language.learn(train.limit(0))
    assert none == [] and {r["lang_pred"] for r in language.identify(train, none, table_).collect()} == {"und"}


# ---- 10 language model ----------------------------------------------------------------------------------------------------------


def test_language_model_counts(spark, given, monkeypatch):
    monkeypatch.setattr(gru_lm, "HEAD", 3000)  # so that most words go through the join
    d = given[0].select("doc_id", "text").unionByName(docs(spark, [*ODD, ODD[4]]).select((F.col("doc_id") + 100000).alias("doc_id"), "text"))
    texts = {r["doc_id"]: WORD.findall((r["text"] or "").translate(LOW)) + [None] for r in d.collect()}
    c = collections.Counter(w for i, t in texts.items() if zlib.crc32(str(i).encode()) % 10 for w in t)
    n, v = sum(c.values()), len(c)
    got = gru_lm.language_model(d).collect()
    assert len(got) == len(texts)
    for r in got:
        t = texts[r["doc_id"]]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(t), sum(c[w] > 0 for w in t), n)
        assert abs(r["base_score"] - sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t)) < 1e-6 * len(t)
        assert r["score"] < 0
    held = [r for r in got if r["held_out"] and r["doc_id"] < 100000]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def test_network_gradient_and_whole_probability():
    rng = np.random.default_rng(0)
    net = gru_lm.Network(50, seed=1)
    for k in net.p:
        net.p[k] = net.p[k].astype(np.float64)
    ids = rng.integers(0, 50, (5, 3))
    ids[2, 1] = gru_lm.REST
    prev = np.concatenate([np.zeros((1, 3), int), ids[:-1]])

    def loss():
        h, total = np.zeros((3, gru_lm.STATE)), 0.0
        gx = net.p["entry"][prev] @ net.p["wx"] + net.p["b"]
        for t in range(5):
            h = np.where((prev[t] == 0)[:, None], 0.0, h)
            h = net.step(gx[t], h)[0]
            total -= net.outputs(h, ids[t]).sum()
        return total / ids.size

    seen = {}
    saved = {k: v.copy() for k, v in net.p.items()}
    net.moments = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in net.p.items()}
    net.train_window(ids, prev, np.zeros((3, gru_lm.STATE)), 0.0)
    for k in net.p:
        seen[k] = net.moments[k][0] / 0.1
    for k, at in (("wh", (2, 5)), ("wx", (3, 40)), ("entry", (int(ids[0, 0]), 2)), ("wc", (1, 3)), ("wo", (int(ids[1, 1]), 4)), ("b", (7,))):
        net.p = {x: v.copy() for x, v in saved.items()}
        net.p[k][at] += 1e-5
        up = loss()
        net.p[k][at] -= 2e-5
        down = loss()
        assert abs((up - down) / 2e-5 - seen[k][at]) < 1e-4, k
    net.p = saved
    h = rng.normal(size=(1, gru_lm.STATE))
    every = np.r_[np.arange(50), gru_lm.REST]
    assert abs(np.exp(net.outputs(np.repeat(h, 51, 0), every)).sum() - 1) < 1e-9


def test_score_carries_the_state():
    net = gru_lm.Network(30, seed=2)
    rng = np.random.default_rng(3)
    texts = [np.r_[rng.integers(1, 30, k), 0].astype(np.int16) for k in (0, 3, 70, 24, 23, 120)]
    off = np.r_[0, np.cumsum([len(t) for t in texts])]
    got = net.score(np.concatenate(texts), off, lanes=4)
    for t, g in zip(texts, got):
        h, prev, total = np.zeros((1, gru_lm.STATE), np.float32), 0, 0.0
        for w in t:
            h = net.step(net.p["entry"][[prev]] @ net.p["wx"] + net.p["b"], h)[0]
            total += float(net.outputs(h, np.array([int(w)]))[0])
            prev = int(w)
        assert abs(total - g) < 1e-3


def test_scoring_pools_batches_whole(monkeypatch):
    """Every row once and in order, whatever the sizes; and outputs far from zero stay numbers with their maxima."""
    monkeypatch.setattr(gru_lm, "POOL", 5)
    batches = [pa.RecordBatch.from_arrays([pa.array(range(lo, lo + n), pa.int64()), pa.array(["x" * 9] * n, pa.string())], ["i", "t"]) for lo, n in ((0, 3), (3, 0), (3, 4), (7, 9), (16, 1))]
    got = list(gru_lm.pooled(iter(batches)))
    assert [b.num_rows for b in got] == [7, 9, 1] and [i for b in got for i in b.column(0).to_pylist()] == list(range(17))
    monkeypatch.setattr(gru_lm, "POOL_BYTES", 1)
    assert [b.num_rows for b in gru_lm.pooled(iter(batches))] == [3, 4, 9, 1]
    net = gru_lm.Network(gru_lm.WORDS)
    h, ids = np.tanh(np.random.default_rng(2).normal(size=(50, gru_lm.STATE))).astype(np.float32), np.arange(50) * 80
    small = net.outputs(h, ids)
    monkeypatch.setattr(gru_lm, "BOUND", -1)
    assert np.allclose(small, net.outputs(h, ids), atol=1e-5)
    net.p["bc"] += np.float32(500)
    net.p["bo"] -= np.float32(500)
    monkeypatch.undo()
    assert np.allclose(small, net.outputs(h, ids), atol=1e-3)


def test_counts_are_looked_up_for_other_words_only():
    """The network's own words take their counts by id; outputs come back in the order that they were asked for."""
    rng = np.random.default_rng(4)
    head = np.sort(rng.integers(-1 << 62, 1 << 62, 500))
    found, log = gru_lm.counted(np.r_[head[::-1], head + 1], head, np.arange(500))
    assert found[:500].all() and not found[500:].any() and not log[500:].any()
    assert np.array_equal(log[:500], np.log10(np.arange(500)[::-1] + 0.1))
    assert not any(x.any() for x in gru_lm.counted(head, head[:0], head[:0]))
    net = gru_lm.Network(gru_lm.WORDS)
    h, ids = np.tanh(rng.normal(size=(300, gru_lm.STATE))).astype(np.float32), rng.integers(0, gru_lm.WORDS + 1, 300)
    alone = [net.outputs(h[i : i + 1], ids[i : i + 1], learn=True) for i in range(300)]
    out, grads, dh = net.outputs(h, ids, learn=True)
    assert np.allclose(out, [x[0][0] for x in alone], atol=1e-4) and np.allclose(dh, np.concatenate([x[2] for x in alone]), atol=1e-4)
    assert all(np.allclose(v, sum(x[1][k] for x in alone), atol=1e-3) for k, v in grads.items())


def test_network_sees_every_training_text(spark, monkeypatch):
    """All texts count, also beyond the 2,500 that were once the bound, and a word that a single partition has moves."""
    seen = []
    kept = gru_lm.one_round
    monkeypatch.setattr(gru_lm, "one_round", lambda *a: seen.append(kept(*a)) or seen[-1])
    monkeypatch.setattr(gru_lm, "CHUNK", 5000)
    monkeypatch.setattr(gru_lm, "FAN", 2)  # several levels of sums
    d = spark.range(6000).repartition(5).selectExpr("id AS doc_id", "concat('the cat ', id % 7, CASE WHEN id = 4321 THEN repeat(' rare bird', 40) ELSE '' END) AS text")
    _, totals, own, count, _, _ = gru_lm.corpus(d)
    net = gru_lm.train_network(d, own, count)
    assert len(seen) == gru_lm.ROUNDS and (sum(seen) == count).all() and count.sum() == totals.n == 24080
    fresh = gru_lm.start(count, len(own) + 1)
    rare = [i + 1 for i in range(len(own)) if count[i + 1] == 40]
    assert len(rare) == 2 and np.abs(net.p["entry"][rare] - fresh.p["entry"][rare]).max() > 0.02
    assert not any(len(x) for x in gru_lm.language_model(d.limit(0)).collect())
    assert all(np.isfinite(v).all() and v.dtype == np.float32 for v in net.p.values())


@pytest.mark.parametrize("module,step,column,rows", [(toxicity, "learn", "toxic", 11000), (quality, "fit", "quality", 5500)])
def test_samples_keep_their_bounds(spark, monkeypatch, module, step, column, rows):
    """As many labelled rows as the bounds name, 12,000 and 6,000, are all learned from."""
    seen, real = [], getattr(module, step)
    monkeypatch.setattr(module, step, lambda *a: seen.append([len(x) for x in a]) or real(*a))
    d = spark.range(rows).selectExpr("id AS doc_id", "concat('word ', id % 5, IF(id % 3 = 0, ' bad', ' good')) AS text")
    module.train(d, d.selectExpr("doc_id", f"IF(doc_id % 3 = 0, 1, 0) AS {column}"), modulus=1, left_out=-1)
    assert rows in seen[0]


def test_word_vectors_equal_loops(monkeypatch):
    """Sums of the neighbours' index vectors, whatever the block, the vectors from them, and the pooled means."""
    rng = np.random.default_rng(1)
    monkeypatch.setattr(quality, "BITS", 8)
    bucket, owner = rng.integers(0, 256, 600), np.sort(rng.integers(0, 9, 600))
    place, sign = quality.index_vectors()
    dense = np.zeros((256, quality.DIM))
    for b in range(256):
        for p, s in zip(place[b], sign[b]):
            dense[b, p] += s
    want = np.zeros((256, quality.DIM))
    for i in range(600):
        for j in range(max(0, i - quality.NEAR), min(600, i + quality.NEAR + 1)):
            if i != j and owner[i] == owner[j]:
                want[bucket[i]] += dense[bucket[j]]
    for block in (37, 1 << 18):
        monkeypatch.setattr(quality, "BLOCK", block)
        total = np.zeros((256, quality.DIM), np.int64)
        quality.neighbours(bucket, owner, total)
        assert (total == want).all()
    seen = np.bincount(bucket, minlength=256)
    context = want - want.sum(0) / 600 * seen[:, None]
    norm = np.linalg.norm(context, axis=1)
    vectors = quality.word_vectors(total, seen)
    assert np.allclose(vectors, dense / quality.ONES**0.5 + context / np.maximum(norm, 1e-9)[:, None], atol=1e-5)
    pooled = quality.pool(vectors, bucket, owner, 11)
    assert all(np.allclose(pooled[t], vectors[bucket[owner == t]].mean(0), atol=1e-5) for t in range(9)) and not pooled[9:].any()


def test_quality_network_gradient_and_temperature():
    """A step of the network moves against the difference quotient of its loss, and the temperature is the best of its grid."""
    rng = np.random.default_rng(2)
    x, y = rng.normal(size=(160, 5)), (rng.random(160) < 0.5).astype(float)
    x[:, 0] += 2 * y
    net = quality.fit(x, y, epochs=20)
    order = np.random.default_rng(3).permutation(160)
    held = order[:20]
    net30 = quality.fit(np.r_[x, x], np.r_[y, y], epochs=20)
    order = np.random.default_rng(3).permutation(320)
    held = order[:40]
    logit, label = net30.logits(np.r_[x, x][held]), np.r_[y, y][held]
    loss = lambda heat: np.logaddexp(0, np.where(label > 0, -1, 1) * logit / heat).mean()
    assert loss(net30.heat) <= min(loss(h) for h in np.exp(np.linspace(-1.0, 2.0, 61))) + 1e-12
    z = (x - net.mean) / net.scale

    def total(w1):
        t = np.tanh(z @ w1 + net.b1) @ net.w2 + net.b2
        return np.logaddexp(0, np.where(y > 0, -1, 1) * t).mean()

    h = np.tanh(z @ net.w1 + net.b1)
    err = (1 / (1 + np.exp(-(h @ net.w2 + net.b2))) - y) / len(y)
    grad = z.T @ (np.outer(err, net.w2) * (1 - h * h))
    for i, j in ((0, 0), (3, 7), (4, 20)):
        up, down = net.w1.copy(), net.w1.copy()
        up[i, j] += 1e-5
        down[i, j] -= 1e-5
        assert abs((total(up) - total(down)) / 2e-5 - grad[i, j]) < 1e-7


def test_quality_from_vectors_alone(spark):
    """Held-out order of the classifier, with the signs of words as tokens and from words and marks alone."""
    sf = "/root/testdata/sf0.1"
    d, marks = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    y = marks.groupBy("doc_id").agg(F.max("quality").alias("y"))
    for signs, least in ((True, 0.99), (False, 0.95)):
        got = quality.score(d, quality.train(d, marks, signs=signs)).where("pmod(crc32(cast(cast(doc_id as string) as binary)), 4) = 2").join(y, "doc_id").toPandas()
        rank, one = got.score.rank(), got.y == 1
        auc = (rank[one].sum() - one.sum() * (one.sum() + 1) / 2) / (one.sum() * (~one).sum())
        assert auc > least, (signs, auc)


def test_machine_score_equals_the_double_sum():
    rng = np.random.default_rng(4)
    model = toxicity.Machine(-0.7)
    known = rng.permutation(1 << toxicity.BITS)[:50]
    model.index[known] = np.arange(50)
    model.w, model.v = rng.normal(size=50), rng.normal(size=(50, toxicity.FACTORS))
    texts = [np.sort(rng.choice(np.r_[known, rng.integers(0, 1 << toxicity.BITS, 20)], rng.integers(0, 12), replace=False)) for _ in range(30)]
    owner = np.repeat(np.arange(30), [len(t) for t in texts])
    got = model.raw(np.concatenate(texts).astype(np.int64), owner, 30)
    for t, z in zip(texts, got):
        at = [int(model.index[b]) for b in t if model.index[b] >= 0]
        want = model.bias + sum(model.w[i] for i in at) + sum(model.v[i] @ model.v[j] for i, j in itertools.combinations(at, 2))
        assert abs(z - want) < 1e-9


def test_machine_without_pairs_is_worse():
    """The pairs, not the terms alone, find most of what is held out."""
    rng = random.Random(8)
    groups, insults = [f"group{i}" for i in range(4)], [f"insult{i}" for i in range(4)]
    texts, y = [], []
    for _ in range(4000):
        a, b = rng.random() < 0.4, rng.random() < 0.4
        words = [f"filler{rng.randrange(200)}" for _ in range(10)] + [rng.choice(groups)] * a + [rng.choice(insults)] * b
        rng.shuffle(words)
        texts.append(" ".join(words))
        y.append(int(a and b))
    texts, y = pa.array(texts), np.array(y)
    found = [toxicity.terms(slab) for slab in textkit.slabs(texts[:3000])]
    sizes = np.concatenate([np.bincount(o, minlength=len(slab)) for (_, o), slab in zip(found, textkit.slabs(texts[:3000]), strict=True)])
    model = toxicity.learn(y[:3000], np.concatenate([b for b, _ in found]), np.r_[0, np.cumsum(sizes)])
    whole = toxicity.score_batch(texts[3000:], model) >= 0.5
    model.v = model.v * 0
    alone = toxicity.score_batch(texts[3000:], model) >= 0.5
    held = y[3000:] == 1
    assert (whole == held).mean() > 0.97 and (whole == held).mean() > (alone == held).mean() + 0.02


def test_mixture_equals_all_subsets():
    """Shares by expectation-maximisation against a plain loop, and the chosen set against every subset of languages."""
    rng = np.random.default_rng(6)
    logp = np.log(rng.dirichlet(np.full(1 << language.BITS, 0.05), 3).T + 1e-9).astype(np.float32)
    text = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega"
    slab = next(textkit.slabs(pa.array([text])))
    bucket, first, _, _ = language.grams(slab)
    words = [logp[bucket[a:b]].sum(0) for a, b in zip(first, [*first[1:], len(bucket)])]
    units = [sum(words[i : i + language.UNIT_WORDS]) * language.WEIGHT for i in range(0, len(words), language.UNIT_WORDS)]
    like = np.array([np.exp(u - u.max()) for u in np.array(units, float)])

    def em(active, rounds):
        pi = active / active.sum()
        for _ in range(rounds):
            r = like * pi
            pi = np.array([row / row.sum() for row in r]).mean(0)
        return pi, np.log((like * pi).sum(1)).sum()

    pi, ll = language.mixture(like, np.array([0]), np.array([len(like)]), np.ones((1, 3)), 8)
    want, want_ll = em(np.ones(3), 8)
    assert np.allclose(pi[0], want, atol=1e-9) and abs(ll[0] - want_ll) < 1e-9
    best, share, every = language.infer(slab, logp)
    cost = 0.5 * np.log(max(len(like), 2))
    value = {}
    for subset in itertools.product((0, 1), repeat=3):
        if any(subset):
            value[subset] = em(np.array(subset, float), 300)[1] - cost * sum(subset)
    chosen = tuple(int(x > 0) for x in every[0])
    assert value[chosen] >= max(value.values()) - cost and best[0] == every[0].argmax() and abs(every[0].sum() - 1) < 1e-6


def test_machine_learns_a_pair_of_neutral_terms():
    """Each term is as frequent in either label; only whether both or neither occur tells."""
    rng = random.Random(3)

    def drawn():
        texts, y = [], []
        for _ in range(3000):
            a, b = rng.random() < 0.5, rng.random() < 0.5
            words = [f"filler{rng.randrange(60)}" for _ in range(12)] + ["group"] * a + ["insult"] * b
            rng.shuffle(words)
            texts.append(" ".join(words))
            y.append(int(a == b))
        return pa.array(texts), np.array(y)

    texts, y = drawn()
    found = [toxicity.terms(slab) for slab in packing.slabs(texts)]
    sizes = np.concatenate([np.bincount(owner, minlength=len(slab)) for (_, owner), slab in zip(found, packing.slabs(texts), strict=True)])
    model = toxicity.learn(y, np.concatenate([bucket for bucket, _ in found]), np.r_[0, np.cumsum(sizes)])
    texts, y = drawn()
    assert ((toxicity.score_batch(texts, model) > 0.5) == y).mean() > 0.9
