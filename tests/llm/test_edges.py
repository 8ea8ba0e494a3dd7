"""Null ids, repeated rows, and queries that meet no words at all."""

import zlib

import public_tokenizers
import pytest

from hushgrad.llm import bpe, fingerprints, near_dedup, packing, quality_classifier, quality_rules, sharding, store, substring_dedup, token_counts, token_store

WORD_FILE = public_tokenizers.path("word_bpe_49k.json")
BYTE_FILE = public_tokenizers.path("byte_bpe_50k.json")
LONG = " ".join(f"word{i}" for i in range(30))


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(None, LONG, None, None), (3, LONG, "h", 5), (3, LONG, "h", 5), (4, None, "h", None), (5, "", "h", 0), (2, LONG + " more", "g", 1), (9, "\n\n", "g", 2)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, n_chars long")


def ids(df):
    return sorted(((-1 if r["doc_id"] is None else r["doc_id"]) for r in df.collect()))


ALL = [-1, 2, 3, 3, 4, 5, 9]


def test_every_operator_keeps_every_row(spark, odd):
    folder = store.fresh_path(spark, "odd")
    token_store.write(odd, folder, WORD_FILE)
    none = quality_classifier.follow_the_leader([], quality_classifier.Params())
    assert ids(fingerprints.fingerprint_with_edit(odd)) == ALL
    assert ids(quality_rules.evaluate(odd)[0]) == ALL
    assert ids(packing.pack(odd, WORD_FILE)) == ALL
    assert ids(sharding.shard(odd, 40)) == ALL
    assert ids(token_counts.count_tokens(odd, BYTE_FILE)) == ALL
    assert ids(token_store.read(spark, folder)) == ALL
    assert ids(bpe.encode_decode(odd, WORD_FILE)) == ALL
    assert ids(quality_classifier.score(odd, none)) == ALL


def test_repeated_rows_stay_alike_in_substring_dedup(odd):
    out = [(r["doc_id"], r["n_removed"]) for r in substring_dedup.strip_repeats(odd).collect()]
    # the null id stands first, so it holds the first occurrence
    assert sorted(out, key=str) == sorted([(None, 0), (2, 30), (3, 30), (3, 30), (4, 0), (5, 0), (9, 0)], key=str)
    assert ids(substring_dedup.filter_documents(odd)) == [-1, 2, 4, 5, 9]


def test_near_dedup_of_odd_rows(odd):
    out = {(r["doc_id"], r["component_id"]) for r in near_dedup.components(odd).collect()}
    assert out == {(None, None), (3, None), (2, None), (4, 4), (5, 5), (9, 9)}


def test_sharding_of_null_ids(odd):
    rows = sharding.shard(odd, 40).collect()
    null = next(r for r in rows if r["doc_id"] is None)
    assert null["text_crc32"] == zlib.crc32(LONG.encode()) and 0 <= null["shard"] < 40


def test_values_of_odd_rows(spark, odd):
    """What repeated rows and rows without id or text get, value by value."""
    import hashlib

    from tokenizers import Tokenizer

    texts = {None: LONG, 3: LONG, 4: "", 5: "", 2: LONG + " more", 9: "\n\n"}
    rows = lambda df: [(r["doc_id"], r) for r in df.collect()]
    word, byte = Tokenizer.from_file(WORD_FILE), Tokenizer.from_file(BYTE_FILE)
    for i, r in rows(bpe.encode_decode(odd, WORD_FILE)):
        assert r["n_tokens"] == len(word.encode(texts[i], add_special_tokens=False).ids) and r["decoded"] == word.decode(word.encode(texts[i], add_special_tokens=False).ids, skip_special_tokens=False)
    for i, r in rows(token_counts.count_tokens(odd, BYTE_FILE)):
        assert (r["n_bytes"], r["n_tokens"]) == (len(texts[i]), len(byte.encode(texts[i], add_special_tokens=False).ids))
    for i, r in rows(quality_rules.evaluate(odd)[0]):
        assert r["n_words"] == len(texts[i].split()) and r["base_failed"] == (len(texts[i].split()) < 10)
    for i, r in rows(packing.pack(odd, WORD_FILE)):
        assert (r["piece"], r["start"], r["length"]) == (0, 0, len(word.encode(texts[i], add_special_tokens=False).ids) + 1)
    # in order of id, null first, each edited by the one after it
    got = rows(fingerprints.fingerprint_with_edit(odd))
    order = [None, 2, 3, 3, 4, 5, 9]
    want = sorted(hashlib.sha256((texts[a][: len(texts[a]) - len(texts[a]) // 4] + texts[b][: len(texts[a]) // 4]).encode()).hexdigest() for a, b in zip(order, order[1:] + order[:1], strict=True))
    assert sorted(r["edited_sha256"] for _, r in got) == want
    same = {i: r["fingerprint"] for i, r in got}
    assert same[None] == same[3] != same[2] and same[4] == same[5] == same[9]
    folder = store.fresh_path(spark, "odd-values")
    token_store.write(odd, folder, WORD_FILE)
    at = 0
    for i, r in sorted(rows(token_store.read(spark, folder)), key=lambda x: x[1]["start"]):
        assert r["start"] == at and i == order.pop(0) and r["n_tokens"] == len(word.encode(texts[i], add_special_tokens=False).ids) + 1
        at += r["n_tokens"]


def test_the_least_long_is_an_id_and_null_is_none(spark):
    least = -(1 << 63)
    df = spark.createDataFrame([(least, LONG), (None, "other " + LONG), (7, "text")], "doc_id long, text string")
    folder = store.fresh_path(spark, "least")
    token_store.write(df, folder, WORD_FILE)
    assert [r["doc_id"] for r in sorted(token_store.read(spark, folder).collect(), key=lambda r: r["start"])] == [None, least, 7]
    assert {r["doc_id"] for r in substring_dedup.strip_repeats(df).collect()} == {None, least, 7}
    assert {r["doc_id"] for r in near_dedup.components(df).collect()} == {None, least, 7}


def test_rows_that_share_an_id(spark):
    """Rows of one id, or of none, are documents of their own; rows equal in id and text are alike."""
    a, b = (" ".join(f"{c}{i}" for i in range(40)) for c in "ab")
    rows = [(1, a), (1, b), (1, b), (2, a), (2, b + " tail"), (None, b), (None, a + " x"), (None, a)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    for _ in range(2):
        left = near_dedup.deduplicate(df).collect()
        # of each group one text without an id stays: nulls come first
        assert len(left) == 2 and {r["doc_id"] for r in left} == {None} and {r["text"][:2] for r in left} == {"a0", "b0"}
    cut = {(r["doc_id"], r["kept_text"], r["n_removed"]) for r in substring_dedup.strip_repeats(df).collect()}
    assert sum(n == 0 for _, _, n in cut) == 2  # one whole a and one whole b, both without an id
    assert (2, "tail", 40) in cut and (1, "", 40) in cut


def test_filter_documents_of_substring_dedup(spark):
    """Texts, lengths and columns of what is left."""
    passage = " ".join(f"p{i}" for i in range(25))
    rows = [(1, f"one\t{passage}  end", "s", 99), (2, f"two {passage} tail", None, 98), (3, passage, "s", 97), (4, None, "s", None), (5, "a  b", "s", 4)]
    df = spark.createDataFrame(rows, "doc_id int, text string, slice string, n_chars int")
    out = {r["doc_id"]: tuple(r) for r in substring_dedup.filter_documents(df).collect()}
    assert out == {1: rows[0], 2: (2, "two tail", None, 8), 4: rows[3], 5: rows[4]}
    assert substring_dedup.filter_documents(df).schema == df.schema


def test_quality_rules_without_a_host(odd):
    assert ids(quality_rules.filter_documents(odd, host_col=None)) == [-1, 2, 3, 3]
