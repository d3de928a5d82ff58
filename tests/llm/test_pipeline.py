"""The pipeline, stage by stage, against what each stage promises."""

import re
from collections import Counter
from pathlib import Path

import pytest
from pyspark.sql import functions as F

import corpus_pipeline as P
from calseries.llm import common, line_rules, toxicity
from calseries.llm.common import staged

from ..conftest import SMALL
from .test_operators import LONG, ODD, brute_components


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    raw = docs
    for name, stage in P.STAGES:
        out = staged(stage(spark, docs, SMALL), "test")
        if name == "quality rules":
            want = {r["doc_id"] for r in line_rules.judge(docs, *line_rules.train(raw, labels)).where("kept").collect()}
            assert {r["doc_id"] for r in out.collect()} == want
        if name == "toxicity":
            score = toxicity.score(docs, toxicity.train(raw, labels, modulus=1, left_out=-1))
            assert {r["doc_id"] for r in out.collect()} == {r["doc_id"] for r in score.where("score < 0.7").collect()}
        if name == "n-gram Jaccard join":
            got = brute_components({r["doc_id"]: r["text"] for r in docs.collect()}, 5, 80)
            assert sorted(r["doc_id"] for r in out.collect()) == sorted(i for i, (_, c) in got.items() if c == i)
        if name != "best-fit packing":
            assert out.schema == raw.schema
            docs = out
        else:
            assert Counter(r["doc_id"] for r in out.where("piece = 0").collect()) == Counter(r["doc_id"] for r in docs.collect())
    assert P.ORACLE_SQL is None and len(P.STAGES) == 5


#: Names that stages use themselves.
CLASHES = ["kept_id", "kept_text", "mix_source", "mix_times", "mix_copy", "score", "kept", "n", "f1", "key", "part", "size", "round", "piece", "block"]


def odd_documents(spark):
    """Clean documents, twice each, and rows with nulls in any column, without text, very long, or with an id again."""
    clean = [r["text"] for r in spark.read.parquet(f"{SMALL}/documents.parquet").where("length(text) BETWEEN 300 AND 900").orderBy("doc_id").limit(12).collect()]
    rows = [(i, t, "s") for i, t in enumerate(clean)] * 2 + [(100 + i, t, None) for i, t in enumerate(ODD)]
    rows += [(None, clean[0], "s"), (None, None, None), (3, clean[7], "t"), (200, LONG + " end", "t"), (201, None, "t")]
    df = spark.createDataFrame([(i, t, None, s, None) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    return df.select("*", *[F.lit(k).alias(c) for k, c in enumerate(CLASHES)])


@pytest.mark.parametrize("name,stage", P.STAGES)
def test_stages_on_odd_rows(spark, name, stage):
    docs = odd_documents(spark)
    given = Counter((r["doc_id"], r["text"], r["source"]) for r in docs.collect())
    out = stage(spark, docs, SMALL)
    none = stage(spark, docs.limit(0), SMALL)
    assert none.columns == out.columns and none.count() == 0
    if name == "best-fit packing":
        got = out.collect()
        assert Counter(r["doc_id"] for r in got if r["piece"] == 0) == Counter(i for i, _, _ in given.elements())
        ends = Counter()
        for r in got:
            ends[r["sequence_id"]] += r["length"]
        assert max(ends.values()) <= 1024 and all(r["offset"] + r["length"] <= ends[r["sequence_id"]] for r in got)
        return
    assert out.columns == docs.columns
    assert all(tuple(r[c] for c in CLASHES) == tuple(range(len(CLASHES))) for r in out.select(*CLASHES).collect())
    got = Counter((r["doc_id"], r["text"], r["source"]) for r in out.collect())
    assert set(got) <= set(given)
    if name == "quality rules":
        kept = {(r["doc_id"], r["n_words"]): r["kept"] for r in line_rules.judge(docs, *line_rules.train(spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet"))).collect()}
        assert got == Counter({k: n for k, n in given.items() if kept[k[0], len(k[1].split()) if k[1] else 0]})
        assert not any(not (t or "").strip() for _, t, _ in got)
    elif name == "toxicity":
        assert all(got[k] == given[k] for k in got) and got[(None, None, None)] == 1 and got[(201, None, "t")] == 1
    elif name == "n-gram Jaccard join":
        assert set(got.values()) == {1}
        assert {k for k in given if k[0] is None or not (k[1] or "").strip()} <= set(got)
        texts = {k: k[1] for k in given if k[0] is not None and (k[1] or "").strip()}
        ids = {k: n for n, k in enumerate(sorted(texts))}
        classes = {c for _, c in brute_components({ids[k]: t for k, t in texts.items()}, 5, 80).values() if c is not None}
        assert len([k for k in got if k in ids]) == len(classes)
    else:
        words = lambda rows: sum(len((t or "").split()) * n for (_, t, s), n in rows.items() if s == "s")
        assert all(n <= 2 * given[k] for k, n in got.items()) and words(got) <= 2 * words(given)


def test_staging_hands_native_memory_back(spark, monkeypatch):
    """What the driver's JVM has freed beside its heap doesn't stay with it: the pipeline's driver went over 1,500 MB."""
    jvm, calls, trim = spark.sparkContext._jvm, [], common.trim
    field = jvm.java.lang.Class.forName("sun.misc.Unsafe").getDeclaredField("theUnsafe")
    field.setAccessible(True)
    unsafe, pid, size = field.get(None), jvm.java.lang.ProcessHandle.current().pid(), 60_000

    def resident():
        return int(re.search(r"RssAnon:\s+(\d+)", Path(f"/proc/{pid}/status").read_text())[1]) / 1024

    def measured(session):
        before = resident()
        trim(session)
        calls.append(before - resident())

    monkeypatch.setattr(common, "trim", measured)
    given = [unsafe.allocateMemory(size) for _ in range(3000)]
    for at in given:
        unsafe.setMemory(at, size, 1)
    for at in given[::2]:  # those between stay, so that the allocator can't shrink by itself
        unsafe.freeMemory(at)
    assert staged(spark.range(10), "test").count() == 10
    for at in given[1::2]:
        unsafe.freeMemory(at)
    assert len(calls) == 1 and calls[0] > 40, calls
