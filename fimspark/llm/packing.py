"""Cost-balanced packing of token sequences.

A document becomes its token ids and one end id. Each map task packs what it reads, in
shards of a bounded number of tokens, so nothing is shuffled and no group can grow with the data.

In a shard of T tokens there are T // capacity full sequences. Whole blocks of a long document fill a
sequence of their own; what is left of each document is dealt in descending length to the sequence of
lowest estimated cost (linear + quadratic in the length of each piece) that still has room for it.
A piece that fits nowhere whole is cut over the cheapest sequences with room. What exceeds the full
sequences goes, in order, to sequences whose lengths are the powers of two that add up to it.
So no sequence has padding.

Null or empty texts are one piece: the end id. Repeated rows are packed each on its own. Null doc_id is passed on.
"""

from __future__ import annotations

import sys
import unicodedata
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import pick, table

CAPACITY = 4096
END_ID = 2
SHARD_TOKENS = 1 << 21
#: Relative cost of one token in the linear layers and of one pair of tokens in attention.
LINEAR_COST, QUADRATIC_COST = 1.0, 1.0 / 2048
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
CACHED_WORDS = 400_000
#: White space in str.split() that the tokenizer's pattern does not count as such.
ODD_SPACE = "\x1c\x1d\x1e\x1f"


PROBES = ("a", "The", "don't", "tokenizers", "12,345.67", "x-y_z", "caf\u00e9", "\u65e5\u672c\u8a9e", "supercalifragilistic", "!!??", "\U0001f600")


class WordTokenizer:
    """Ids of a word-end BPE tokenizer file.

    The file's rules treat white-space separated chunks independently, so chunks are cached. Chunks not seen
    before are split by the file's own pattern and merged by a byte-pair engine that is given the file's vocabulary;
    chunks with special strings or with letters whose lower case depends on the context go through the `tokenizers` library whole.
    The engine's single-piece call is not a documented one: it is tried on PROBES first, and where it is missing or differs from the library, the library does all texts.
    """

    def __init__(self, path: str):
        import json

        import regex
        import tiktoken
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.pattern = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.special = [x["content"] for x in spec["added_tokens"]]
        visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
        hidden = [b for b in range(256) if b not in set(visible)]
        as_byte = {chr(b): b for b in visible} | {chr(256 + k): b for k, b in enumerate(hidden)}
        ranks = {}
        for token, i in spec["model"]["vocab"].items():
            if token not in self.special:
                ends = token.endswith("</w>") and token != "</w>"
                ranks[bytes(as_byte[x] for x in (token[:-4] if ends else token)) + b"\xff" * ends] = i
        ranks.setdefault(b"\xff", max(ranks.values()) + 100)
        self.engine = getattr(tiktoken.Encoding("words", pat_str=r"(?s).+", mergeable_ranks=ranks, special_tokens={}), "_core_bpe", None)
        self.cache: dict[str, bytes] = {}
        self.trusted = hasattr(self.engine, "encode_single_piece") and all(self.chunk(w) == self.whole(w) for w in PROBES)

    def whole(self, text: str) -> bytes:
        return np.asarray(self.library.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def chunk(self, word: str) -> bytes:
        if "<|" in word or "Σ" in word or "İ" in word:
            return self.whole(word)
        out: list[int] = []
        for piece in self.pattern.findall(unicodedata.normalize("NFC", word).lower() if not word.isascii() else word.lower()):
            out += self.engine.encode_single_piece(piece.encode() + b"\xff")
        return np.asarray(out, "<u4").tobytes()

    def ids(self, text: str) -> bytes:
        """The ids as little-endian unsigned 32-bit numbers."""
        if not self.trusted or any(x in text for x in ODD_SPACE):
            return self.whole(text)
        words, cache = text.split(), self.cache
        try:
            return b"".join(map(cache.__getitem__, words))
        except KeyError:
            pass
        if len(cache) > CACHED_WORDS:
            cache.clear()
        out = []
        for w in words:
            got = cache.get(w)
            if got is None:
                got = self.chunk(w)
                if len(w) < 64:
                    cache[w] = got
            out.append(got)
        return b"".join(out)


_tokenizers: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """One for each Python worker: workers are reused, and the cache with them."""
    if path not in _tokenizers:
        _tokenizers[path] = WordTokenizer(path)
    return _tokenizers[path]


def plan(lengths: np.ndarray, capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int]]:
    """(document, start, length, sequence, offset) of each piece; sequences count from 0."""
    lengths = np.asarray(lengths, np.int64)
    pieces: list[tuple[int, int, int, int, int]] = []
    seq = 0
    for d in np.flatnonzero(lengths >= capacity):
        for start in range(0, int(lengths[d]) // capacity * capacity, capacity):
            pieces.append((int(d), start, capacity, seq, 0))
            seq += 1
    rest = lengths % capacity
    total = int(rest.sum())
    m = total // capacity
    order = [int(d) for d in np.argsort(-rest, kind="stable") if rest[d]]
    cost, room = np.zeros(m), np.full(m, capacity, np.int64)
    loose: list[tuple[int, int, int]] = []

    def put(s: int, d: int, start: int, n: int) -> None:
        pieces.append((d, start, n, seq + s, int(capacity - room[s])))
        room[s] -= n
        cost[s] += LINEAR_COST * n + QUADRATIC_COST * n * n

    for d in order:
        n = int(rest[d])
        start = int(lengths[d]) - n
        if m:
            where = np.where(room >= n, cost, np.inf)
            s = int(where.argmin())
            if where[s] < np.inf:
                put(s, d, start, n)
                continue
        loose.append((d, start, n))
    tail: list[tuple[int, int, int]] = []
    full = np.flatnonzero(room > 0).tolist()
    full.sort(key=lambda s: cost[s], reverse=True)
    for d, start, n in loose:
        while n and full:
            s = full[-1]
            took = int(min(n, room[s]))
            put(s, d, start, took)
            start, n = start + took, n - took
            if not room[s]:
                full.pop()
        if n:
            tail.append((d, start, n))
    seq += m
    left = total - m * capacity
    sizes = [1 << b for b in range(left.bit_length() - 1, -1, -1) if left >> b & 1]
    at = 0
    for d, start, n in tail:
        while n:
            took = min(n, sizes[0] - at)
            pieces.append((d, start, took, seq, at))
            start, n, at = start + took, n - took, at + took
            if at == sizes[0]:
                sizes.pop(0)
                seq, at = seq + 1, 0
    return pieces


def _packed(path: str, end_id: int, capacity: int, shard_tokens: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        tok, end = tokenizer(path), np.asarray([end_id], "<u4").tobytes()
        first = (TaskContext.get().partitionId() if TaskContext.get() else 0) << 32
        docs: list[int | None] = []
        ids: list[bytes] = []
        held = 0

        def shard() -> pa.RecordBatch:
            nonlocal first
            lengths = np.asarray([len(x) // 4 for x in ids], np.int64)
            pieces = plan(lengths, capacity)
            d, start, length, seq, offset = (np.asarray(x, np.int64) for x in zip(*pieces, strict=True))
            crc = [zlib.crc32(memoryview(ids[i])[4 * s : 4 * (s + n)]) for i, s, n, *_ in pieces]
            out = pa.RecordBatch.from_arrays(
                [pa.array([docs[i] for i in d], pa.int64()), pa.array(start), pa.array(length), pa.array(crc, pa.int64()), pa.array(lengths[d]), pa.array(seq + first), pa.array(offset)],
                names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"],
            )
            first += int(seq.max()) + 1
            docs.clear()
            ids.clear()
            return out

        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                x = tok.ids(text.as_py() or "") + end
                docs.append(doc)
                ids.append(x)
                held += len(x) // 4
                if held >= shard_tokens:
                    yield shard()
                    held = 0
        if docs:
            yield shard()

    return run


def pack(docs: DataFrame, path: str | None = None, end_id: int = END_ID, capacity: int = CAPACITY, shard_tokens: int = SHARD_TOKENS) -> DataFrame:
    """One row for each piece; see the module's text. sequence_id is unique over all tasks and shards."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    return pick(docs, "doc_id", "text").selectExpr("cast(doc_id as long) doc_id", "cast(text as string) text").mapInArrow(_packed(path, end_id, capacity, shard_tokens), SCHEMA)


def op8_packing(spark, sf_dir) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"))


assert sys.byteorder == "little", "ids are written as native unsigned 32-bit numbers"
