"""Each operator against a plain version in Python."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from hushgrad.llm import bpe, fingerprints, near_dedup, packing, quality_classifier, quality_rules, sharding, store, substring_dedup, token_counts, token_store, words

WORD = re.compile(r"[^\x20\x09-\x0D]+")
WORD_FILE = public_tokenizers.path("word_bpe_49k.json")
BYTE_FILE = public_tokenizers.path("byte_bpe_50k.json")


def plain_words(t):
    return WORD.findall(t or "")


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_jump_hash(spark, docs, rows, empty):
    def jump(key, n):
        key, b, j = key % 2**64, -1, 0
        while j < n:
            b = j
            key = (key * sharding.MULTIPLIER + 1) % 2**64
            j = int((b + 1) * (float(1 << 31) / float((key >> 33) + 1)))
        return b

    out = by_id(sharding.shard(docs, 40))
    assert len(out) == len(rows)
    slots = collections.defaultdict(list)
    for i, t in rows:
        r = out[i]
        assert (r["shard"], r["grown_shard"]) == (jump(i, 40), jump(i, 41))
        assert r["size"] == len((t or "").encode()) + 16 and r["text_crc32"] == zlib.crc32((t or "").encode())
        slots[r["shard"]].append(r["slot"])
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    big = spark.range(-500, 500).selectExpr("id * 7919 as doc_id", "'' as text")
    got = by_id(sharding.shard(big, 40))
    assert all(r["shard"] == jump(k, 40) and r["grown_shard"] in (r["shard"], 40) for k, r in got.items())
    assert sharding.shard(empty, 40).count() == 0


def base_rules(t):
    w = plain_words(t)
    seen, dup = set(), 0
    for line in (t or "").split("\n"):
        if plain_words(line):
            dup += line in seen
            seen.add(line)
    wins = collections.defaultdict(list)
    for i in range(len(w) - 4):
        wins[tuple(w[i : i + 5])].append(i)
    hit = {j for v in wins.values() if len(v) > 1 for i in v for j in range(i, i + 5)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), dup, len(hit)


def test_quality_rules(spark, docs, rows, empty):
    rules = quality_rules.Rules(min_line_docs=2, line_share=0.1, min_left=0.5)
    verdicts, hot = quality_rules.evaluate(docs, rules)
    out = by_id(verdicts)
    hosts = collections.defaultdict(lambda: collections.defaultdict(set))
    texts = collections.defaultdict(set)
    host = {i: (f"h{i % 3}" if i % 7 else "") for i, _ in rows}
    norm = lambda line: tuple(x.decode("utf-8", "surrogateescape") for x in (words.LOWER[np.frombuffer(line.encode(), dtype=np.uint8)].tobytes()).split())
    for i, t in rows:
        texts[host[i]].add(t or "")
        for line in (t or "").split("\n"):
            if plain_words(line):
                hosts[host[i]][norm(line)].add(t)
    limit = {h: max(2, 0.1 * len(texts[h])) for h in texts}
    above = {(h, k) for h in hosts for k, v in hosts[h].items() if len(v) > limit[h]}
    assert hot.count() == len(above) > 0
    for i, t in rows:
        r = out[i]
        n, chars, sym, dup, rep = base_rules(t)
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (n, chars, sym, dup, rep), i
        failed = n < 10 or 100 * rep > 20 * n
        gone = sum(len(plain_words(x)) for x in (t or "").split("\n") if (host[i], norm(x)) in above)
        assert r["base_failed"] == failed and r["n_line_words_removed"] == gone
        assert r["kept"] == (not failed and n - gone >= 0.5 * n)
    kept = by_id(quality_rules.filter_documents(docs, rules))
    assert set(kept) == {i for i, r in out.items() if r["kept"]}
    for i, t in rows:
        if i in kept:
            assert kept[i]["text"] == "\n".join(x for x in t.split("\n") if (host[i], norm(x)) not in above)
            assert kept[i]["n_chars"] == len(kept[i]["text"]) and kept[i]["lines"] == "clash"
    assert quality_rules.evaluate(empty, rules)[0].count() == 0 and quality_rules.filter_documents(empty, rules).count() == 0


def strip(rows, k=20):
    seen, out = set(), {}
    for i, t in sorted(rows, key=lambda r: r[0]):
        w = plain_words(t)
        gone = set()
        for a in range(len(w) - k + 1):
            x = tuple(w[a : a + k])
            if x in seen:
                gone.update(range(a, a + k))
            seen.add(x)
        out[i] = (len(w), len(gone), " ".join(x for j, x in enumerate(w) if j not in gone))
    return out


@pytest.mark.parametrize("entries", [2048, 4])
def test_substring_dedup(docs, rows, empty, entries):
    p = substring_dedup.Params(part_entries=entries, slice_bytes=1 << 14)
    want = strip(rows)
    for i, r in by_id(substring_dedup.strip_repeats(docs, p)).items():
        assert (r["n_words"], r["n_removed"], r["kept_text"]) == want[i], i
    for i, r in by_id(substring_dedup.strip_repeats(docs, p, digest=True)).items():
        assert r["kept_sha256"] == hashlib.sha256(want[i][2].encode()).hexdigest()
    kept = by_id(substring_dedup.filter_documents(docs, p))
    assert set(kept) == {i for i, (n, g, s) in want.items() if not g or s}
    assert substring_dedup.strip_repeats(empty, p).count() == 0


@pytest.mark.parametrize("wide", [False, True])
def test_sketch_parts(wide):
    rng = np.random.default_rng(1)
    groups = [np.unique(rng.integers(0, 1 << 20, n)) for n in (3000, 1, 40, 200_000)] + [np.array([0, (1 << 20) - 1])]
    low, high = substring_dedup.compact(np.concatenate(groups), np.array([len(g) for g in groups]), 20, wide)
    for g, x, y in zip(groups, low.to_pylist(), high.to_pylist(), strict=True):
        assert (substring_dedup.expand(x, y, wide) == g).all()


def test_sketch_never_counts_below_the_truth():
    """Windows of two slices that occur twice in all pass in both; few others do."""
    import pyarrow as pa

    rng = random.Random(8)
    shared = " ".join(f"s{i}" for i in range(60))
    texts = [" ".join(f"a{rng.random()}" for _ in range(4000)) + " " + shared, " ".join(f"b{rng.random()}" for _ in range(4000)) + " " + shared]
    p = substring_dedup.Params()
    shape = substring_dedup.Shape.of(80_000, 2, p)
    tables = [pa.table({"slice": pa.array([i], pa.int32()), "text": [t]}) for i, t in enumerate(texts)]
    sent = [x for t in tables for x in substring_dedup._sketch(p, shape)(t).to_pylist()]
    sent.sort(key=lambda x: (x["row"], x["part"]))
    batch = pa.RecordBatch.from_pylist(sent, substring_dedup._arrow(substring_dedup._SKETCH))
    told = pa.Table.from_batches(substring_dedup._merge(shape.part_log2, shape.wide)(iter([batch]))).to_pylist()
    for i, t in enumerate(tables):
        w = substring_dedup.Windows(t.column("text"), p.window)
        side = pa.Table.from_pylist([x for x in told if x["slice"] == i], substring_dedup._arrow(substring_dedup._FLAGS))
        ok = substring_dedup._passing(w, side, p, shape)
        assert ok[w.start >= 4000].all() and ok[w.start < 4000 - 20].mean() < 0.2


def test_sketch_follows_the_text():
    """Cells of a row keep up with any size, and no part of the sketch outgrows a task."""
    p = substring_dedup.Params()
    for size in (10**6, 10**9, 10**11, 10**14):
        shape = substring_dedup.Shape.of(size, 1000, p)
        assert (1 << shape.cells_log2) >= size / substring_dedup.BYTES_PER_WINDOW * p.cells_per_window
        assert shape.part_log2 <= substring_dedup.MOST_PART_LOG2 and size / shape.slices <= 64 << 20


def test_packing(docs, rows, empty):
    tok = Tokenizer.from_file(WORD_FILE)
    got = packing.pack(docs, WORD_FILE).collect()
    seqs = collections.defaultdict(list)
    pieces = collections.defaultdict(list)
    for r in got:
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
        pieces[r["doc_id"]].append(r)
    for v in seqs.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= 4096
    total = 0
    for i, t in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 1]
        total += len(ids)
        parts = sorted(pieces[i], key=lambda r: r["piece"])
        assert [r["piece"] for r in parts] == list(range(-(-len(ids) // 4096)))
        for r in parts:
            x = ids[r["start"] : r["start"] + r["length"]]
            assert r["start"] == 4096 * r["piece"] and zlib.crc32(np.array(x, dtype="<u4").tobytes()) == r["ids_crc32"]
    assert len(seqs) <= -(-total // 4096) + 1
    assert packing.pack(empty, WORD_FILE).count() == 0


def test_bin_plan():
    rng = np.random.default_rng(3)
    for _ in range(30):
        cap = int(rng.integers(5, 40))
        h = collections.Counter(rng.integers(1, cap + 1, int(rng.integers(1, 60))).tolist())
        used = collections.Counter()
        for found, times in packing.plan(dict(h), cap):
            assert sum(k * n for k, n in found.items()) <= cap
            for k, n in found.items():
                used[k] += n * times
        assert used == h
        room = int(rng.integers(1, cap + 1))
        best = {0}
        for k, n in h.items():
            best = {s + k * c for s in best for c in range(n + 1) if s + k * c <= room}
        found = packing.fullest(sorted(h, reverse=True), dict(h), room)
        assert sum(k * n for k, n in found.items()) == max(best) and all(n <= h[k] for k, n in found.items())


def shingle_set(t):
    w = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    w = plain_words(w)
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or ({tuple(w)} if w else set())


def group(rows, percent):
    sets = {i: shingle_set(t) for i, t in rows}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in sets}


def test_near_dedup(docs, rows, empty):
    want = group(rows, 85)
    for block in (512, 2):
        out = by_id(near_dedup.components(docs, near_dedup.Params(block=block)))
        assert {i: (r["n_shingles"], r["component_id"]) for i, r in out.items()} == want
        assert all(r["kept"] == (i == r["component_id"]) for i, r in out.items())
    left = near_dedup.deduplicate(docs)
    assert left.columns == docs.columns and {r["doc_id"] for r in left.collect()} == {i for i, (_, c) in want.items() if i == c}
    assert near_dedup.components(empty).count() == 0


def test_near_dedup_large_group_of_near_copies(spark):
    base = [f"w{i}" for i in range(300)]
    rows = []
    for i in range(400):
        w = list(base)
        for j in range(i % 4):
            w[(i * 37 + j * 71) % 300] = f"c{i}x{j}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    out = near_dedup.components(df).collect()
    assert {r["component_id"] for r in out} == {0}


def test_near_dedup_family_around_the_threshold(spark):
    rng = random.Random(2)
    base = [f"w{i}" for i in range(200)]
    rows = []
    for i in range(150):
        w = list(base)
        for j in range(rng.randint(2, 9)):
            w[rng.randrange(200)] = f"c{i}x{j}"
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = {i: c for i, (_, c) in group(rows, 85).items()}
    assert 1 < len(set(want.values())) < 150
    for block in (512, 16):
        out = by_id(near_dedup.components(df, near_dedup.Params(block=block)))
        assert {i: r["component_id"] for i, r in out.items()} == want


def test_fingerprints(docs, rows, empty):
    out = by_id(fingerprints.fingerprint_with_edit(docs))
    assert len(out) == len(rows)
    order = sorted(rows, key=lambda r: r[0])
    for (i, t), (j, u) in zip(order, order[1:] + order[:1], strict=True):
        t, u, r = t or "", u or "", out[i]
        cut = len(t) // 4
        edited = t[: len(t) - cut] + u[:cut]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        a, b, c = (np.array([x[k : k + 4] for k in range(0, len(x), 4)]) for x in (r["fingerprint"], r["edited_fingerprint"], out[j]["fingerprint"]))
        assert r["near_edited"] == (a == b).mean() and r["near_next"] == (a == c).mean()
        x, y = shingle_set(t), shingle_set(edited)
        if t == t.lower() and x and y:
            assert abs(r["near_edited"] - len(x & y) / len(x | y)) < 0.25
    assert out[5]["fingerprint"] == out[6]["fingerprint"]
    assert fingerprints.fingerprint_with_edit(empty).count() == 0


def test_fingerprint_joins(docs, rows):
    """Sets are of words in lower case (A-Z), as near_dedup takes them."""
    want = group(rows, 80)
    out = by_id(fingerprints.near_duplicates(docs))
    assert {i: r["component_id"] for i, r in out.items()} == {i: c for i, (_, c) in want.items()}


def test_token_counts(docs, rows, empty):
    tok = Tokenizer.from_file(BYTE_FILE)
    out = by_id(token_counts.count_tokens(docs, BYTE_FILE))
    for i, t in rows:
        n = len(tok.encode(t or "", add_special_tokens=False).ids)
        r = out[i]
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len((t or "").encode()), n, n > 512), i
    assert token_counts.count_tokens(empty, BYTE_FILE).count() == 0


def test_token_store(spark, docs, rows, empty):
    tok = Tokenizer.from_file(WORD_FILE)
    folder = store.fresh_path(spark, "test-ids")
    token_store.write(docs, folder, WORD_FILE)
    out = by_id(token_store.read(spark, folder))
    crc = by_id(token_store.read(spark, folder, digest=True))
    at = 0
    for i, t in sorted(rows, key=lambda r: r[0]):
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], dtype="<u4")
        assert (out[i]["start"], out[i]["n_tokens"], out[i]["ids"]) == (at, len(ids), ids.tobytes())
        assert crc[i]["ids_crc32"] == zlib.crc32(ids.tobytes())
        at += len(ids)
    folder = store.fresh_path(spark, "test-none")
    token_store.write(empty, folder, WORD_FILE)
    assert token_store.read(spark, folder).count() == 0


def test_variable_length_code():
    """The coding that write and read use, on values of one to four bytes in documents of any length."""
    rng = np.random.default_rng(6)
    edge = np.array([0, 255, 256, 65535, 65536, (1 << 24) - 1, 1 << 24, (1 << 32) - 1, 7], dtype=np.uint32)
    v = np.concatenate([edge, (rng.integers(0, 1 << 32, 500) >> rng.integers(0, 32, 500)).astype(np.uint32)])
    off = np.array([0, 0, 1, 3, 9, 9, 200, len(v)])
    control, data = token_store.coded(v, off)
    assert [len(x) for x in data.to_pylist()] == [int(token_store.byte_lengths(v[a:b]).sum()) for a, b in zip(off, off[1:], strict=False)]
    assert (token_store.decoded(b"".join(control.to_pylist()), b"".join(data.to_pylist()), np.diff(off)) == v).all()


def test_token_files_ascend_by_id(spark, docs, rows):
    folder = store.fresh_path(spark, "test-order")
    token_store.write(docs.withColumn("doc_id", docs["doc_id"] * 7919 - 3_000_000), folder, WORD_FILE)
    files = sorted(spark.read.parquet(f"{folder}/blocks").inputFiles())
    assert len(files) > 4
    seen = []
    for f in files:
        for r in sorted(spark.read.parquet(f).collect(), key=lambda r: r["block"]):
            seen += np.frombuffer(r["doc_ids"], dtype="<i8").tolist()
    assert seen == sorted(i * 7919 - 3_000_000 for i, _ in rows)


def test_wide_ids_through_files(spark, monkeypatch):
    """A vocabulary in which every rank takes three or four bytes, written to files and read back."""
    shift = 1 << 24
    monkeypatch.setattr(token_store, "BLOCK_IDS", 50)
    to = np.arange(60_000, dtype=np.uint32) * 7 + (shift - 100)
    docs = spark.createDataFrame([(i, " ".join(f"wide{j}" for j in range(i))) for i in range(30)], "doc_id long, text string")
    spec = bpe.vocabulary_text(WORD_FILE)
    share = spark.sparkContext.broadcast
    ids = docs.mapInArrow(token_store._encode(share(spec), bpe.style_of(spec), 1, share(to), np.array([0, 10])), "range int, doc_id long, n_tokens long, control binary, data binary")
    folder = store.fresh_path(spark, "test-wide")
    ids.repartitionById(2, ids["range"]).sortWithinPartitions("doc_id").mapInArrow(token_store._blocks, token_store._BLOCK).write.parquet(folder)

    class Back:
        def __getitem__(self, values):
            return ((values.astype(np.int64) - (shift - 100)) // 7).astype(np.uint32)

    back = type("Shared", (), {"value": Back()})()
    tok = Tokenizer.from_file(WORD_FILE)
    blocks = spark.read.parquet(folder).select("range", "start", "n_null", "doc_ids", "lengths", "control", "data")
    got = {}
    for b in token_store._decode(back)(iter(blocks.toArrow().to_batches())):
        got |= dict(zip(b.column(1).to_pylist(), b.column(4).to_pylist(), strict=True))
    assert len(got) == 30
    for i, x in got.items():
        want = [*tok.encode(" ".join(f"wide{j}" for j in range(i)), add_special_tokens=False).ids, 1]
        assert np.frombuffer(x, dtype="<u4").tolist() == want


def test_bpe(docs, rows, empty):
    tok = Tokenizer.from_file(WORD_FILE)
    out = by_id(bpe.encode_decode(docs, WORD_FILE))
    for i, t in rows:
        ids = tok.encode(t or "", add_special_tokens=False).ids
        assert out[i]["n_tokens"] == len(ids) and out[i]["ids"] == np.array(ids, dtype="<u4").tobytes()
        assert out[i]["decoded"] == tok.decode(ids, skip_special_tokens=False)
    assert bpe.encode_decode(empty, WORD_FILE).count() == 0


def test_forced_boundaries_cut_somewhere():
    enc = bpe.encoder(bpe.vocabulary_text(WORD_FILE), "word")
    assert enc.never[ord("q") * 256 + ord("x")] or enc.never.sum() > 50_000


def test_classifier_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = quality_classifier.train(docs, labels)
    got = quality_classifier.score(docs, model).join(labels, "doc_id").filter("held_out").collect()
    right = sum(r["predicted"] == r["quality"] for r in got) / len(got)
    majority = sum(r["quality"] for r in got) / len(got)
    assert right > majority + 0.05


def test_follow_the_leader_by_a_plain_loop():
    """The published per-coordinate update, one coordinate after the other."""
    import math

    p = quality_classifier.Params(bits=4, epochs=2, alpha=0.3, beta=0.7, l1=0.6, l2=0.2)
    rng = np.random.default_rng(9)
    rows = []
    for _ in range(30):
        f = np.sort(rng.choice(16, int(rng.integers(1, 6)), replace=False))
        rows.append((f.astype(np.int32), rng.random(len(f)).astype(np.float32), int(rng.integers(0, 2))))
    z, n = [0.0] * 17, [0.0] * 17

    def weight(i):
        if abs(z[i]) <= p.l1:
            return 0.0
        return -(z[i] - math.copysign(p.l1, z[i])) / ((p.beta + math.sqrt(n[i])) / p.alpha + p.l2)

    order = np.random.default_rng(p.seed)
    for _ in range(p.epochs):
        for k in order.permutation(len(rows)):
            f, v, y = rows[k]
            x = [*zip(f.tolist(), map(float, v), strict=True), (16, 1.0)]
            w = {i: weight(i) for i, _ in x}
            prob = 1 / (1 + math.exp(-sum(w[i] * c for i, c in x)))
            for i, c in x:
                g = (prob - y) * c
                step = (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / p.alpha
                z[i] += g - step * w[i]
                n[i] += g * g
    model = quality_classifier.follow_the_leader(rows, p)
    assert model.weights == pytest.approx([weight(i) for i in range(16)], rel=1e-5, abs=1e-7) and model.bias == pytest.approx(weight(16))
    assert any(model.weights) and not all(model.weights)


def test_scores_are_sparse_dot_products(docs, rows):
    """The score of each text from its n-grams, counted in a dictionary."""
    import math

    p = quality_classifier.Params(bits=10)
    rng = np.random.default_rng(2)
    model = quality_classifier.Model(rng.normal(size=1 << p.bits).astype(np.float32), 0.25, p.bits)
    got = by_id(quality_classifier.score(docs, model, p))
    for i, t in rows:
        s = words.scan(np.frombuffer((t or "").encode(), dtype=np.uint8), np.array([0, len((t or "").encode())]))
        f, _ = quality_classifier.grams(s, p.bits)
        count = collections.Counter(f.tolist())
        dot = sum(model.weights[k] * math.sqrt(c / len(f)) for k, c in count.items())
        assert got[i]["score"] == pytest.approx(1 / (1 + math.exp(-(dot + 0.25))), abs=1e-5)


def test_classifier_edges(docs, empty, spark):
    none = spark.createDataFrame([], "doc_id long, quality int")
    model = quality_classifier.train(docs, none)
    assert {r["score"] for r in quality_classifier.score(docs, model).collect()} == {0.5}
    assert quality_classifier.score(empty, model).count() == 0
    assert quality_classifier.filter_documents(docs, model).columns == docs.columns
