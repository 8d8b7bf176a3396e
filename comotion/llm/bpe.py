"""Byte-level BPE (operator 3): two-tier encoding and decoding from a rank file.

Tier one: a minimal perfect hash over the vocabulary resolves pre-tokens that are tokens already. Tier two: other
pre-tokens become a linked list of bytes whose mergeable neighbours wait in a heap; the lowest rank, leftmost first, merges.
Results of distinct pre-tokens are memoised per worker, in a memo that is emptied when full.

Defined results: null and empty texts encode to no ids (hash of the empty string); repeated rows get equal values; very
long texts are processed whole, one document at a time; texts pass through as UTF-8.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from comotion.llm.common import doc_text, record, slices

MEMO = 700_000
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
IDS_SCHEMA = "doc_id long, ids array<int>"


def read_ranks(path: str) -> list[bytes]:
    """Tokens by rank."""
    with open(path, "rb") as f:
        pairs = [line.split() for line in f if line.strip()]
    tokens = [b""] * len(pairs)
    for token, rank in pairs:
        tokens[int(rank)] = base64.b64decode(token)
    return tokens


def _mix(h: int, seed: int) -> int:
    h = (h ^ (seed * 0x9E3779B97F4A7C15)) & 0xFFFFFFFFFFFFFFFF
    h = ((h ^ (h >> 31)) * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
    return h ^ (h >> 29)


def _key(token: bytes) -> int:
    return int.from_bytes(hashlib.blake2b(token, digest_size=8).digest(), "little")


class PerfectHash:
    """Minimal perfect hash by displacement: n keys, n slots, one seed for each small bucket of keys."""

    def __init__(self, tokens: list[bytes]):
        n = self.n = len(tokens)
        self.buckets = max(1, n // 4)
        keys = [_key(t) for t in tokens]
        groups: list[list[int]] = [[] for _ in range(self.buckets)]
        for i, k in enumerate(keys):
            groups[k % self.buckets].append(i)
        self.seeds, self.slots = [0] * self.buckets, [-1] * n
        free = 0
        for b in sorted(range(self.buckets), key=lambda b: -len(groups[b])):
            own = groups[b]
            if not own:
                break
            if len(own) == 1:  # a lone key takes any free slot by name
                while self.slots[free] >= 0:
                    free += 1
                self.slots[free], self.seeds[b] = own[0], -free - 1
                continue
            seed = 1
            while True:
                spots = [_mix(keys[i], seed) % n for i in own]
                if len(set(spots)) == len(own) and all(self.slots[s] < 0 for s in spots):
                    break
                seed += 1
            self.seeds[b] = seed
            for s, i in zip(spots, own):
                self.slots[s] = i
        self.tokens = tokens

    def get(self, token: bytes) -> int:
        """Rank of the token, or -1."""
        k = _key(token)
        seed = self.seeds[k % self.buckets]
        if not seed:
            return -1
        rank = self.slots[-seed - 1 if seed < 0 else _mix(k, seed) % self.n]
        return rank if self.tokens[rank] == token else -1


class Codec:
    def __init__(self, path: str, pattern: str):
        self.tokens = read_ranks(path)
        self.hash = PerfectHash(self.tokens)
        self.ranks = {t: r for r, t in enumerate(self.tokens)}  # pairs of the slow tier
        self.find = regex.compile(pattern).findall
        self.decimal = [str(r) for r in range(len(self.tokens))]
        self.memo: dict[str, tuple[int, ...]] = {}

    def _merge(self, word: bytes) -> tuple[int, ...]:
        rank, n = self.ranks, len(word)
        part = [word[i : i + 1] for i in range(n)]
        left, right, version = list(range(-1, n - 1)), list(range(1, n + 1)), [0] * n
        heap = [(r, i, 0, 0) for i in range(n - 1) if (r := rank.get(part[i] + part[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, vi, vj = heapq.heappop(heap)
            j = right[i] if version[i] == vi else n
            if j >= n or version[j] != vj:
                continue
            part[i] += part[j]
            part[j], version[j] = b"", -1
            version[i] += 1
            right[i] = right[j]
            if right[i] < n:
                left[right[i]] = i
            for a in (left[i], i):
                b = right[a] if a >= 0 else n
                if b < n and (r := rank.get(part[a] + part[b])) is not None:
                    heapq.heappush(heap, (r, a, version[a], version[b]))
        out, i = [], 0
        while i < n:
            out.append(rank[part[i]])
            i = right[i]
        return tuple(out)

    def word(self, pretoken: str) -> tuple[int, ...]:
        raw = pretoken.encode()
        whole = self.hash.get(raw)
        return (whole,) if whole >= 0 else self._merge(raw)

    def encode(self, text: str) -> list[int]:
        words, memo = self.find(text), self.memo
        if len(memo) > MEMO:
            memo.clear()
        for w in set(words).difference(memo):
            memo[w] = self.word(w)
        return list(chain.from_iterable(map(memo.__getitem__, words)))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> Codec:
    """One codec for each worker process."""
    return Codec(path, pattern)


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and ids of every text."""
    out = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int32()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for b in slices(batches):
            yield record(out, b.column(0), [c.encode(t or "") for t in b.column(1).to_pylist()])

    return doc_text(docs).mapInArrow(run, IDS_SCHEMA)


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and the decoded bytes of every list of ids (null: no ids)."""
    out = pa.schema([("doc_id", pa.int64()), ("decoded", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for b in batches:
            yield record(out, b.column(0), [c.decode(x or []) for x in b.column(1).to_pylist()])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, decoded binary")


def round_trip(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encodes, decodes the ids again, and returns counts and hashes of both in one pass."""
    out = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])
    sha = lambda x: hashlib.sha256(x).hexdigest()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path, pattern)
        for b in slices(batches):
            rows = []
            for text in b.column(1).to_pylist():
                ids = c.encode(text or "")
                rows.append((len(ids), sha(",".join(map(c.decimal.__getitem__, ids)).encode()), sha(c.decode(ids))))
            yield record(out, b.column(0), *zip(*rows))

    return doc_text(docs).mapInArrow(run, SCHEMA)
