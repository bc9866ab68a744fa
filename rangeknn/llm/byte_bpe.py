"""Byte-level BPE encoding and decoding with a two-tier look-up.

First tier: a minimal perfect hash over the vocabulary resolves a pre-token that is itself a
token. Second tier: other pre-tokens are merged on a doubly linked list of byte positions
with a heap of candidate merges, lowest rank first and leftmost among equal ranks.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator
from functools import lru_cache
from pathlib import Path

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .segments import SegmentEncoder

_M64 = (1 << 64) - 1


class PerfectHash:
    """Minimal perfect hash by hash-and-displace: key -> its index in ``keys``, or -1.

    Keys fall into buckets of about four; the buckets, largest first, each take the first
    displacement that sends their keys to free slots. As many slots as keys.
    """

    def __init__(self, keys: list[bytes]) -> None:
        n = max(1, len(keys))
        self.n, self.n_buckets, self.keys = n, n // 4 + 1, keys
        hashes = np.array([xxhash.xxh3_64_intdigest(k) for k in keys], dtype=np.uint64)
        bucket = (hashes % np.uint64(self.n_buckets)).astype(np.int64)
        order = np.argsort(bucket, kind="stable")
        starts = np.searchsorted(bucket[order], np.arange(self.n_buckets + 1))
        self.shift = [0] * self.n_buckets
        self.slot_key = [-1] * n
        for b in np.argsort(-(np.diff(starts)), kind="stable").tolist():
            members = order[starts[b] : starts[b + 1]].tolist()
            if not members:
                break
            own = [int(hashes[i]) for i in members]
            shift = 0
            while True:
                slots = [self._slot(h, shift) for h in own]
                if len(set(slots)) == len(slots) and all(self.slot_key[s] < 0 for s in slots):
                    break
                shift += 1
            self.shift[b] = shift
            for s, i in zip(slots, members, strict=True):
                self.slot_key[s] = i

    def _slot(self, h: int, shift: int) -> int:
        x = (h ^ (shift * 0x9E3779B97F4A7C15)) & _M64
        x = ((x ^ (x >> 32)) * 0xD6E8FEB86659FD93) & _M64
        return (x ^ (x >> 32)) % self.n

    def get(self, key: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(key)
        i = self.slot_key[self._slot(h, self.shift[h % self.n_buckets])]
        return i if i >= 0 and self.keys[i] == key else -1


def unicode_pattern(pattern: str) -> str:
    """The pattern with white space as Unicode's property, as the reference library has it."""
    return pattern.replace(r"[^\s", r"[^\p{White_Space}").replace(r"\s", r"\p{White_Space}").replace(r"(?!\S)", r"(?!\P{White_Space})")


class BytePairCoder:
    def __init__(self, ranks: dict[bytes, int], pattern: str) -> None:
        tokens = list(ranks)
        self.ids = [ranks[t] for t in tokens]
        self.table = PerfectHash(tokens)
        self.pieces = regex.compile(unicode_pattern(pattern)).findall
        self.token_of = dict(zip(self.ids, tokens, strict=True))
        self.memo: dict[str, bytes] = {}
        #: Answers of the perfect hash for short strings of bytes, most of them merge candidates.
        self.ranks: dict[bytes, int] = {}

    def rank(self, token: bytes) -> int:
        if (r := self.ranks.get(token)) is None:
            i = self.table.get(token)
            r = self.ids[i] if i >= 0 else -1
            if len(token) <= 12:
                if len(self.ranks) >= 400_000:
                    self.ranks.clear()
                self.ranks[token] = r
        return r

    def merge(self, piece: bytes) -> list[int]:
        """Ids of a pre-token that is not a token itself."""
        n = len(piece)
        end = list(range(1, n + 1))  # of the part that begins here; 0 once it is merged away
        before = list(range(-1, n - 1))
        heap = []
        for i in range(n - 1):
            if (r := self.rank(piece[i : i + 2])) >= 0:
                heap.append((r, i, i + 1, i + 2))
        heapq.heapify(heap)
        while heap:
            _, i, mid, stop = heapq.heappop(heap)
            if end[i] != mid or mid >= n or end[mid] != stop:
                continue
            end[i], end[mid] = stop, 0
            if stop < n:
                before[stop] = i
                if (r := self.rank(piece[i : end[stop]])) >= 0:
                    heapq.heappush(heap, (r, i, stop, end[stop]))
            if (left := before[i]) >= 0 and (r := self.rank(piece[left:stop])) >= 0:
                heapq.heappush(heap, (r, left, i, stop))
        out, i = [], 0
        while i < n:
            out.append(self.rank(piece[i : end[i]]))
            i = end[i]
        return out

    def encode_piece(self, piece: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        raw = piece.encode()
        whole = self.rank(raw)
        return np.array([whole] if whole >= 0 else self.merge(raw), dtype="<u4").tobytes()

    def encode_segments(self, segments: list[str]) -> list[bytes]:
        memo, out = self.memo, []
        if len(memo) > 400_000:
            for key in list(memo)[100_000:300_000]:
                del memo[key]
        for segment in segments:
            ids = b""
            for piece in self.pieces(segment):
                if (found := memo.get(piece)) is None:
                    found = memo[piece] = self.encode_piece(piece)
                ids += found
            out.append(ids)
        return out

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token_of.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def read_ranks(path: str) -> dict[bytes, int]:
    lines = (line.split() for line in Path(path).read_bytes().splitlines() if line)
    return {base64.b64decode(token): int(rank) for token, rank in lines}


@lru_cache(maxsize=2)
def coder(path: str, pattern: str) -> tuple[BytePairCoder, SegmentEncoder]:
    """One coder for each worker process; the vocabulary bounds its size."""
    own = BytePairCoder(read_ranks(path), pattern)
    return own, SegmentEncoder(own.encode_segments, spaced=True, limit=700_000)


def _batches(batches: Iterator[pa.RecordBatch], path: str, pattern: str, with_ids: bool) -> Iterator[pa.RecordBatch]:
    own, segments = coder(path, pattern)
    for batch in batches:
        texts = batch.column("text").to_pylist()
        for at in range(0, len(texts), 1000):
            n, sha, back, kept = [], [], [], []
            for parts in segments.values(texts[at : at + 1000]):
                ids = b"".join(parts)
                n.append(len(ids) // 4)
                sha.append(hashlib.sha256(ids).hexdigest())
                back.append(hashlib.sha256(own.decode(ids)).hexdigest())
                if with_ids:
                    kept.append(np.frombuffer(ids, "<u4").astype(np.int32))
            columns = [batch.column("id").slice(at, 1000), pa.array(n, pa.int64()), pa.array(sha, pa.string()), pa.array(back, pa.string())]
            names = ["id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                columns, names = [*columns, pa.array(kept, pa.list_(pa.int32()))], [*names, "ids"]
            yield pa.RecordBatch.from_arrays(columns, names=names)


def encode_decode(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per row of docs: id, n_tokens, digests of the ids and of the decoded bytes.

    Null texts count as empty and have no ids; every row gives one row, repeated or not; an
    empty table gives none; other columns are ignored. ``with_ids`` adds the ids themselves.
    No exchange: texts are encoded where they are read.
    """
    id_type = docs.schema[id_col].dataType.simpleString()
    schema = f"id {id_type}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    texts = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    return texts.mapInArrow(lambda batches: _batches(batches, ranks_path, pattern, with_ids), schema).withColumnRenamed("id", id_col)


def decode_ids(rows: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, ids array<int>) -> (id, decoded binary); null ids give null, unknown ids an error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, _ = coder(ranks_path, pattern)
        for batch in batches:
            out = [None if ids is None else own.decode(np.array(ids, "<u4").tobytes()) for ids in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(out, pa.binary())], names=["id", "decoded"])

    id_type = rows.schema[id_col].dataType.simpleString()
    return rows.select(F.col(id_col).alias("id"), F.col(ids_col).alias("ids")).mapInArrow(run, f"id {id_type}, decoded binary").withColumnRenamed("id", id_col)
