"""Texts beyond a slice of half a megabyte, through every operator, against plain versions."""

import collections
import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from test_operators import base_rules, by_id, group, strip
from tokenizers import Tokenizer

from hushgrad.llm import bpe, fingerprints, near_dedup, packing, quality_classifier, quality_rules, sharding, store, substring_dedup, token_counts, token_store, words

WORD_FILE = public_tokenizers.path("word_bpe_49k.json")
BYTE_FILE = public_tokenizers.path("byte_bpe_50k.json")


@pytest.fixture(scope="module")
def long_rows():
    rng = random.Random(12)
    text = lambda n: "\n".join(" ".join(f"{rng.choice('abcdefgh')}{rng.randrange(10**5)}" for _ in range(12)) for _ in range(n))
    big = text(9000)
    assert len(big) > 1.2 * words.SLICE_BYTES
    w = big.split(" ")
    w[50] = "changed"
    return [(1, big), (2, " ".join(w)), (3, "short text"), (4, text(7000) + "\n" + big[:5000]), (5, "x" * (words.SLICE_BYTES + 100)), (6, " " * (words.SLICE_BYTES + 7))]


@pytest.fixture(scope="module")
def long_docs(spark, long_rows):
    return spark.createDataFrame([(i, t, "h", len(t)) for i, t in long_rows], "doc_id long, text string, source string, n_chars long").repartition(2)


def test_rules_and_substring_and_near(long_docs, long_rows):
    out = by_id(quality_rules.evaluate(long_docs)[0])
    for i, t in long_rows:
        assert tuple(out[i][k] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == base_rules(t)
    want = strip(long_rows)
    for i, r in by_id(substring_dedup.strip_repeats(long_docs)).items():
        assert (r["n_words"], r["n_removed"], r["kept_text"]) == want[i]
    assert want[2][1] > 100_000 and want[4][1] > 500
    near = {i: (r["n_shingles"], r["component_id"]) for i, r in by_id(near_dedup.components(long_docs)).items()}
    assert near == group(long_rows, 85) and near[2][1] == 1


def test_fingerprints_and_shards_and_scores(long_docs, long_rows):
    out = by_id(fingerprints.fingerprint_with_edit(long_docs))
    for (i, t), (_, u) in zip(long_rows, long_rows[1:] + long_rows[:1], strict=True):
        cut = len(t) // 4
        assert out[i]["n_chars"] == len(t) and out[i]["edited_sha256"] == hashlib.sha256((t[: len(t) - cut] + u[:cut]).encode()).hexdigest()
    assert out[1]["near_next"] > 0.95
    sizes = by_id(sharding.shard(long_docs, 40))
    assert all(sizes[i]["text_crc32"] == zlib.crc32(t.encode()) for i, t in long_rows)
    model = quality_classifier.follow_the_leader([], quality_classifier.Params())
    assert {r["score"] for r in quality_classifier.score(long_docs, model).collect()} == {0.5}


def test_tokens(spark, long_docs, long_rows):
    word, byte = Tokenizer.from_file(WORD_FILE), Tokenizer.from_file(BYTE_FILE)
    counts = by_id(token_counts.count_tokens(long_docs, BYTE_FILE))
    coded = by_id(bpe.encode_decode(long_docs, WORD_FILE))
    folder = store.fresh_path(spark, "long-ids")
    token_store.write(long_docs, folder, WORD_FILE)
    back = by_id(token_store.read(spark, folder))
    pieces = collections.defaultdict(dict)
    for r in packing.pack(long_docs, WORD_FILE).collect():
        pieces[r["doc_id"]][r["piece"]] = r
    at = 0
    for i, t in long_rows:
        assert counts[i]["n_tokens"] == len(byte.encode(t, add_special_tokens=False).ids)
        ids = word.encode(t, add_special_tokens=False).ids
        assert coded[i]["ids"] == np.array(ids, dtype="<u4").tobytes() and coded[i]["decoded"] == word.decode(ids, skip_special_tokens=False)
        ids = np.array([*ids, 1], dtype="<u4")
        assert (back[i]["start"], back[i]["ids"]) == (at, ids.tobytes())
        at += len(ids)
        for k, r in pieces[i].items():
            assert r["ids_crc32"] == zlib.crc32(ids[4096 * k : 4096 * (k + 1)].tobytes())
        assert len(pieces[i]) == -(-len(ids) // 4096)
