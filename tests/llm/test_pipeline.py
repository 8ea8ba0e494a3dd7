"""The pipeline's stages on a small table, each against a plain version on its own input."""

import collections
import zlib

import corpus_pipeline
import numpy as np
import public_tokenizers
from test_operators import group, plain_words, strip
from tokenizers import Tokenizer

from hushgrad.llm import quality_classifier, quality_rules, store, words


def norm(line):
    return tuple(x.decode("utf-8", "surrogateescape") for x in words.LOWER[np.frombuffer(line.encode(), dtype=np.uint8)].tobytes().split())


def plain_rules(rows, near):
    """What the first stage leaves: base rules, then lines above the limit of their host, a group of near copies as one document."""
    unit = {i: c for i, (_, c) in group([(i, t) for i, (t, _) in rows.items()], near.percent).items()}
    first = {}
    for i in sorted(rows):  # equal texts are one unit even without words
        first.setdefault(rows[i][0], i)
    name = lambda i: unit[first[rows[i][0]]]
    lines, docs = collections.defaultdict(set), collections.defaultdict(set)
    for i, (t, host) in rows.items():
        docs[host].add(name(i))
        for x in t.split("\n"):
            if plain_words(x):
                lines[host, norm(x)].add(name(i))
    r = quality_rules.Rules()
    above = {k for k, v in lines.items() if len(v) > r.min_line_docs and len(v) > r.line_share * len(docs[k[0]])}
    out = {}
    for i, (t, host) in rows.items():
        w = plain_words(t)
        seen = collections.Counter(tuple(w[j : j + 5]) for j in range(len(w) - 4))
        rep = {p for j in range(len(w) - 4) if seen[tuple(w[j : j + 5])] > 1 for p in range(j, j + 5)}
        kept = [x for x in t.split("\n") if (host, norm(x)) not in above]
        left = sum(len(plain_words(x)) for x in kept)
        if len(w) >= 10 and 100 * len(rep) <= 20 * len(w) and left >= r.min_left * len(w):
            out[i] = "\n".join(kept)
    return out


def test_stages(spark):
    d = "/root/testdata/sf0.001"
    docs = first = spark.read.parquet(f"{d}/documents.parquet")
    seen = [first.count()]
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: (r["text"] or "", r["source"] or "") for r in docs.collect()}
        old = docs
        docs = store.settle(stage(spark, docs, d), name)
        got = docs.collect()
        seen.append(len(got))
        if name != "best_fit_packing":
            assert docs.columns == first.columns and docs.dtypes == first.dtypes
            assert all(r["n_chars"] == len(r["text"]) for r in got)
            texts = {r["doc_id"]: r["text"] for r in got}
            assert len(texts) == len(got)
        if name == "quality_rules":
            assert texts == plain_rules(before, corpus_pipeline.NEAR)
        if name == "quality_classifier":
            model = quality_classifier.train(old, spark.read.parquet(f"{d}/labels.parquet"))
            assert set(texts) == {r["doc_id"] for r in quality_classifier.score(old, model).filter("predicted = 1").collect()}
            assert all(texts[i] == before[i][0] for i in texts)
        if name == "minhash_near_dedup":
            want = group([(i, t) for i, (t, _) in before.items()], 80)
            assert texts == {i: before[i][0] for i, (_, c) in want.items() if i == c}
        if name == "substring_dedup":
            want = strip([(i, t) for i, (t, _) in before.items()])
            assert texts == {i: (s if gone else before[i][0]) for i, (_, gone, s) in want.items() if s or not gone}
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    sequences, total = collections.defaultdict(list), 0
    pieces = collections.defaultdict(dict)
    for r in got:
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
        pieces[r["doc_id"]][r["piece"]] = r
    assert set(pieces) == set(before)
    for i, (t, _) in before.items():
        ids = [*tok.encode(t, add_special_tokens=False).ids, 1]
        total += len(ids)
        assert sorted(pieces[i]) == list(range(-(-len(ids) // 4096)))
        for k, r in pieces[i].items():
            x = ids[4096 * k : 4096 * (k + 1)]
            assert (r["start"], r["length"], r["ids_crc32"]) == (4096 * k, len(x), zlib.crc32(np.array(x, dtype="<u4").tobytes()))
    for parts in sequences.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(sequences) <= -(-total // 4096) + 1
    assert seen[0] > seen[1] and seen[1] >= seen[2] >= seen[3] >= seen[4] > 0
