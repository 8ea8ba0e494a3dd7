"""Inputs on which less than the whole job was done before."""

import hashlib
import random

import corpus_pipeline
import pyarrow as pa
import pytest
from test_operators import group

from hushgrad.llm import fingerprints, quality_rules, store


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def replaced(w, at, tag):
    w = list(w)
    for i in at:
        w[i] = f"{tag}x{i}"
    return " ".join(w)


def test_near_stage_links_from_eight_tenths(spark):
    rng = random.Random(3)
    rows = []
    for g in range(40):
        base = [f"g{g}w{i}" for i in range(200)]
        rows.append((10 * g, " ".join(base)))
        # a changed word takes five of 196 shingles: 2 to 6 of them leave 0.90 to 0.73
        rows += [(10 * g + k, replaced(base, range(20, 20 + 10 * rng.randint(2, 6), 10), f"c{k}")) for k in (1, 2)]
    want, at_85 = group(rows, 80), group(rows, 85)
    kept = {i for i, (_, c) in want.items() if i == c}
    assert len(kept) < len({c for _, c in at_85.values()})
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert set(by_id(corpus_pipeline.apply_near_dedup(spark, df, ""))) == kept


def test_fingerprints_of_hashed_ids(spark):
    rng = random.Random(4)
    ids = [rng.randrange(1 << 62) for _ in range(2000)] + [-(1 << 63) + 1, (1 << 63) - 1, (1 << 63) - 2]
    rows = [(i, f"text {i} " + " ".join(rng.choice("abc") for _ in range(12))) for i in ids]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    bounds = fingerprints.id_bounds(df.select("doc_id"), 12)
    assert len(bounds) > 6 and set(bounds.tolist()) <= set(ids)
    out = by_id(fingerprints.fingerprint_with_edit(df))
    assert len(out) == len(rows)
    order = sorted(rows)
    for (i, t), (_, u) in zip(order, order[1:] + order[:1], strict=True):
        cut = len(t) // 4
        assert out[i]["edited_sha256"] == hashlib.sha256((t[: len(t) - cut] + u[:cut]).encode()).hexdigest()


def test_fingerprints_refuse_a_range_without_next():
    cols = {"bucket": [0, 0, 1, 1], "lead": [0, 0, 0, 1], "doc_id": [1, 2, 3, 1], "text": ["a", "b", "c", "a"]}
    batch = pa.RecordBatch.from_pydict(cols)
    with pytest.raises(ValueError, match="no next document for 2"):
        list(fingerprints._with_next(fingerprints.Params())(iter([batch])))
    with pytest.raises(ValueError, match="no next document for 3"):
        list(fingerprints._with_next(fingerprints.Params())(iter([batch.slice(2, 1)])))


def test_one_of_a_large_group_of_near_copies_survives(spark):
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    alone = docs
    for _, stage in corpus_pipeline.STAGES[:3]:
        alone = store.settle(stage(spark, alone, d), "alone")
    # the longest text of many lines that passes the stages
    model = max((r for r in alone.collect() if r["text"].count("\n") > 4), key=lambda r: len(r["text"])).asDict()
    lines, rows = model["text"].split("\n"), []
    at = [(k, j) for k, x in enumerate(lines) for j in range(len(x.split()))]
    for i in range(60):
        copy = [x.split(" ") for x in lines]
        k, j = at[i * 7 % len(at)]
        copy[k][min(j, len(copy[k]) - 1)] = f"changed{i}"
        text = "\n".join(map(" ".join, copy))
        rows.append({**model, "doc_id": 10**6 + i, "text": text, "source": "one.example", "n_chars": len(text)})
    boiler = "all rights reserved by the owners of this page"
    for i in range(60):
        text = "\n".join(" ".join(f"u{i}v{k}w{j}" for j in range(12)) for k in range(6)) + "\n" + boiler
        rows.append({**model, "doc_id": 2 * 10**6 + i, "text": text, "source": "one.example", "n_chars": len(text)})
    group_ = spark.createDataFrame(rows, docs.schema)
    verdicts, hot = quality_rules.evaluate(group_)
    assert not any(r["kept"] for r in verdicts.collect() if r["doc_id"] < 2 * 10**6) and hot.count() > 1
    verdicts, hot = quality_rules.evaluate(group_, near=corpus_pipeline.NEAR)
    assert all(r["kept"] for r in verdicts.collect()) and [r["n_docs"] for r in hot.collect()] == [60]
    now = docs.filter(docs["doc_id"] != model["doc_id"]).union(group_)
    for _, stage in corpus_pipeline.STAGES[:3]:
        now = store.settle(stage(spark, now, d), "with-group")
    assert [r["doc_id"] for r in now.collect() if 10**6 <= r["doc_id"] < 2 * 10**6] == [10**6]
