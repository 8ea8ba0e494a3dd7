"""BPE encoding by forced-boundary splitting, and decoding.

A pair of adjacent bytes that occurs inside no vocabulary token can never end up
inside one token of an encoding, so the place between them is a certain cut:
merges on both sides never meet.  Pre-tokens are cut at all such places, the
fragments are encoded independently (each distinct fragment once, then from a
cache) and the ids are concatenated.  A fragment that ends its pre-token is
encoded with the vocabulary's word end, an inner one without.

Texts with an unassigned code point or a special token's string are encoded by
the library as they are.
"""

from __future__ import annotations

import hashlib
import json
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hushgrad.llm import pretokens, words

U = np.uint64


def vocabulary_text(path: str) -> str:
    """The file's content, read on the driver; tasks get it inside their function."""
    with open(path, encoding="utf-8") as f:
        return f.read()


def byte_names() -> list[str]:
    """The printable character that byte-level vocabularies use for each byte: itself where it is
    printable Latin-1, else the next free one from 256 on."""
    keep = {*range(33, 127), *range(161, 173), *range(174, 256)}
    names, extra = [], 0
    for b in range(256):
        names.append(chr(b) if b in keep else chr(256 + extra))
        extra += b not in keep
    return names


class Fragments:
    """Ids of byte strings by hash, in flat arrays; emptied when full, so memory is bounded."""

    SLOTS = 1 << 21
    LIMIT = 700_000

    def __init__(self) -> None:
        self.clear()

    def clear(self) -> None:
        self.key = np.zeros(self.SLOTS, dtype=U)
        self.slot = np.zeros(self.SLOTS, dtype=np.int32)
        self.ids = np.zeros(1 << 20, dtype=np.int32)
        self.begin = np.zeros(1 << 16, dtype=np.int64)
        self.size = np.zeros(1 << 16, dtype=np.int32)
        self.n = self.used = 0

    def add(self, ids: list[list[int]]) -> np.ndarray:
        """New entries; returns their numbers."""
        sizes = np.fromiter(map(len, ids), dtype=np.int32, count=len(ids))
        flat = np.fromiter((x for y in ids for x in y), dtype=np.int32, count=int(sizes.sum()))
        while self.used + len(flat) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        while self.n + len(ids) > len(self.begin):
            self.begin, self.size = np.concatenate([self.begin, np.zeros_like(self.begin)]), np.concatenate([self.size, np.zeros_like(self.size)])
        self.ids[self.used : self.used + len(flat)] = flat
        to = slice(self.n, self.n + len(ids))
        self.begin[to] = self.used + np.cumsum(sizes) - sizes
        self.size[to] = sizes
        self.used += len(flat)
        self.n += len(ids)
        return np.arange(to.start, to.stop)

    def look(self, h: np.ndarray) -> np.ndarray:
        """Entry number for each hash, -1 where it is unknown."""
        at = (h & U(self.SLOTS - 1)).astype(np.int64)
        return np.where((self.key[at] == h) & (h != 0), self.slot[at], -1)

    def remember(self, h: np.ndarray, number: np.ndarray) -> None:
        at = (h & U(self.SLOTS - 1)).astype(np.int64)
        self.key[at] = h
        self.slot[at] = number


class Encoder:
    """A tokenizers file, ready to encode slices of texts.  style: how it pre-tokenizes."""

    def __init__(self, spec: str, style: str) -> None:
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        os.environ.setdefault("RAYON_NUM_THREADS", "1")
        from tokenizers import Tokenizer

        self.style = style
        j = json.loads(spec)
        j["truncation"] = j["padding"] = None
        self.whole = Tokenizer.from_str(json.dumps(j))
        self.specials = [t["content"] for t in j["added_tokens"]]
        suffix = j["model"].get("end_of_word_suffix")
        bare = j | {"normalizer": None, "pre_tokenizer": None, "post_processor": None, "added_tokens": []}
        self.last = Tokenizer.from_str(json.dumps(bare)).model
        self.inner = self.last
        if suffix:
            self.inner = Tokenizer.from_str(json.dumps(bare | {"model": j["model"] | {"end_of_word_suffix": None}})).model
        names = byte_names()
        self.name = {i: c for i, c in enumerate(names)}
        back = {c: i for i, c in enumerate(names)}
        #: never[a * 256 + b]: no token has byte b right after byte a
        self.never = np.ones(65536, dtype=bool)
        for token in j["model"]["vocab"]:
            if suffix:
                token = token.removesuffix(suffix)
            codes = [back[c] for c in token if c in back]
            for a, b in zip(codes, codes[1:], strict=False):
                self.never[a * 256 + b] = False
        top = max([*j["model"]["vocab"].values(), *(t["id"] for t in j["added_tokens"])]) + 1
        self.token_text = [b""] * top
        for token, i in [*j["model"]["vocab"].items(), *((t["content"], t["id"]) for t in j["added_tokens"])]:
            self.token_text[i] = token.encode()
        self.vocabulary = top
        self.cache = Fragments()

    def _resolve(self, h: np.ndarray, data: np.ndarray, start: np.ndarray, end: np.ndarray, ends_word: np.ndarray) -> np.ndarray:
        """The cache entry of each fragment, encoding those not seen before."""
        if self.cache.n > Fragments.LIMIT:
            self.cache.clear()
        number = self.cache.look(h)
        miss = np.flatnonzero(number < 0)
        if len(miss):
            new, at, back = np.unique(h[miss], return_index=True, return_inverse=True)
            pick = miss[at]
            raw = data.tobytes()
            out = []
            for a, b, z in zip(start[pick].tolist(), end[pick].tolist(), ends_word[pick].tolist(), strict=True):
                text = raw[a:b].decode("latin-1").translate(self.name)
                out.append([t.id for t in (self.last if z else self.inner).tokenize(text)])
            made = self.cache.add(out)
            self.cache.remember(new, made)
            number[miss] = made[back]
        return number

    def odd(self, texts: list[str], flagged: np.ndarray) -> np.ndarray:
        odd = flagged.copy()
        for i, t in enumerate(texts):
            if "<|" in t and any(x in t for x in self.specials):
                odd[i] = True
        return odd

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts, where each text's begin), as the library gives them without special tokens added."""
        shaped = [pretokens.lowered(t) for t in texts] if self.style == "word" else texts
        t = pretokens.split(shaped, self.style)
        odd = self.odd(texts, t.odd)
        data = t.data
        # certain cuts inside pre-tokens
        cut = np.zeros(len(data) + 1, dtype=bool)
        cut[1:-1] = self.never[(data[:-1].astype(np.uint16) << 8) | data[1:]]
        depth = np.zeros(len(data) + 1, dtype=np.int8)
        depth[t.start] = 1
        depth[t.end] -= 1  # starts and ends are each distinct, so no entry is counted twice
        cut &= np.cumsum(depth, dtype=np.int8) > 0
        cut[t.start] = True
        start = np.flatnonzero(cut)
        closes = np.zeros(len(data) + 1, dtype=bool)
        closes[t.end] = True
        # a fragment ends where the next one begins or where its pre-token ends, whichever comes first
        stops = np.flatnonzero(cut | closes)
        end = stops[np.flatnonzero(cut[stops]) + 1]
        ends_word = closes[end]
        h = words.span_hash(data, start, end, 0)
        h = np.where(ends_word, h, words.mix(h ^ U(0x5BD1E9955BD1E995)))
        number = self._resolve(h, data, start, end, ends_word)
        sizes = self.cache.size[number].astype(np.int64)
        total = np.concatenate([[0], np.cumsum(sizes)])
        ids = self.cache.ids[np.repeat(self.cache.begin[number] - total[:-1], sizes) + np.arange(total[-1])]
        # documents by fragment
        edge = t.start[np.minimum(t.first, len(t.start) - 1)] if len(t.start) else t.first
        first = np.where(t.first < len(t.start), np.searchsorted(start, edge), len(start)) if len(t.start) else np.zeros(len(texts) + 1, dtype=np.int64)
        offsets = total[first]
        if odd.any():
            parts, lengths = [], []
            for i, text in enumerate(texts):
                part = ids[offsets[i] : offsets[i + 1]]
                if odd[i]:
                    part = np.array(self.whole.encode(text, add_special_tokens=False).ids, dtype=np.int32)
                parts.append(part)
                lengths.append(len(part))
            ids, offsets = np.concatenate(parts), np.concatenate([[0], np.cumsum(lengths)])
        return ids.astype(np.uint32), offsets

    def decode(self, ids: np.ndarray) -> str:
        """As the library's decode with special tokens kept: without a decoder, tokens joined by blanks."""
        if self.whole.decoder is not None:
            return self.whole.decode(ids.tolist(), skip_special_tokens=False)
        table = self.token_text
        return b" ".join([table[i] for i in ids.tolist()]).decode("utf-8", "replace")


_encoders: dict[tuple[int, int, str], Encoder] = {}


def encoder(spec: str, style: str) -> Encoder:
    """One per worker process."""
    key = (len(spec), zlib.crc32(spec.encode()), style)
    if key not in _encoders:
        _encoders[key] = Encoder(spec, style)
    return _encoders[key]


def encoded(column: pa.Array, enc: Encoder) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(from row, to row, ids, offsets) over a text column without nulls."""
    for a, b in words.slices(column, 1 << 20):
        ids, offsets = enc.encode(column.slice(a, b - a).to_pylist())
        yield a, b, ids, offsets


def as_bytes(ids: np.ndarray) -> bytes:
    return ids.astype("<u4").tobytes()


def style_of(spec: str) -> str:
    """How a file splits: 'byte' for a plain byte-level pattern, 'word' for the lower-case word pattern."""
    pre = json.loads(spec)["pre_tokenizer"]
    return "byte" if pre["type"] == "ByteLevel" else "word"


def _round_trip(spec_shared, style: str):  # noqa: ANN001
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(spec_shared.value, style)
        for batch in batches:
            for a, b, ids, offsets in encoded(words.as_texts(batch.column(1)), enc):
                coded, back = [], []
                for i in range(b - a):
                    part = ids[offsets[i] : offsets[i + 1]]
                    coded.append(as_bytes(part))
                    back.append(enc.decode(part))
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, b - a), pa.array(np.diff(offsets).astype(np.int64)), pa.array(coded, pa.binary()), pa.array(back, pa.string())],
                    ["doc_id", "n_tokens", "ids", "decoded"],
                )

    return run


def _digests(spec_shared, style: str):  # noqa: ANN001
    @words.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _round_trip(spec_shared, style)(batches):
            sha = [pa.array([hashlib.sha256(x.as_buffer()).hexdigest() for x in batch.column(c)], pa.string()) for c in (2, 3)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], *sha], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def encode_decode(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", digest: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids (little-endian unsigned 32-bit), decoded; with digest their sha256 instead.

    A map over documents without a shuffle.  Null texts are empty and have no
    ids; ids of documents pass through as they are, nulls and repeats included;
    an empty table gives no rows.
    """
    spec = vocabulary_text(path)
    shared = docs.sparkSession.sparkContext.broadcast(spec)
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    kind = docs.schema[id_col].dataType.simpleString()
    if digest:
        return rows.mapInArrow(_digests(shared, style_of(spec)), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
    return rows.mapInArrow(_round_trip(shared, style_of(spec)), f"doc_id {kind}, n_tokens long, ids binary, decoded string")
