"""Byte-level BPE: encoding by a two-tier lookup, and decoding.

Tier one is a minimal perfect hash over the vocabulary: a whole pre-token that is an
entry costs one hash, one displacement and one comparison. Tier two merges what is
left by a heap of ranked pairs over a linked list of byte pieces, in n log n for any
length of pre-token.

Defined results: null counts as the empty text, which has no ids and decodes to no
bytes; texts are encoded whole; repeated rows are encoded each; an empty table gives an
empty result; further columns of the input are kept out of it.
"""

from __future__ import annotations

import base64
from collections.abc import Iterable, Iterator
from heapq import heapify, heappop, heappush

from pyspark.sql import DataFrame

from strata.llm.common import map_texts, worker_cache

#: Pre-tokens in each half of what a worker remembers, and the longest it keeps.
MOST_KNOWN, LONGEST_KNOWN = 300_000, 64


def parse_ranks(lines: Iterable[bytes]) -> dict[bytes, int]:
    """Lines of base64 token and rank."""
    return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


class PerfectHash:
    """Hash and displace: keys fall into small buckets; the largest bucket first, each gets the first
    displacement that puts all its keys on free slots. Lone keys take the slots that remain."""

    def __init__(self, keys: list[bytes], per_bucket: int = 3):
        self.size, self.n_buckets = max(1, len(keys)), max(1, len(keys) // per_bucket)
        self.slots: list[bytes | None] = [None] * self.size
        self.shift = [0] * self.n_buckets
        buckets: list[list[tuple[int, int, bytes]]] = [[] for _ in range(self.n_buckets)]
        for key in keys:
            b, x, y = self._hash(key)
            buckets[b].append((x, y, key))
        order = sorted((b for b in range(self.n_buckets) if buckets[b]), key=lambda b: -len(buckets[b]))
        free = None
        for b in order:
            own = buckets[b]
            if len(own) > 1:
                d = 0
                while True:
                    at = {self._at(x, y, d) for x, y, _ in own}
                    if len(at) == len(own) and all(self.slots[k] is None for k in at):
                        break
                    d += 1
                for x, y, key in own:
                    self.slots[self._at(x, y, d)] = key
                self.shift[b] = d
            else:
                if free is None:
                    free = (k for k in range(self.size) if self.slots[k] is None)
                k = next(free)
                self.slots[k] = own[0][2]
                self.shift[b] = -k - 1

    def _hash(self, key: bytes) -> tuple[int, int, int]:
        import xxhash

        h = xxhash.xxh3_128_intdigest(key)
        return (h & 0xFFFFFFFF) % self.n_buckets, h >> 32 & 0xFFFFFFFF, (h >> 64 & 0xFFFFFFFF) | 1

    def _at(self, x: int, y: int, d: int) -> int:
        return ((x ^ d * 0x9E3779B97F4A7C15) * y >> 24 & 0xFFFFFFFFFF) % self.size

    def slot(self, key: bytes) -> int:
        """The slot of a key, or -1 if it is none of the keys."""
        b, x, y = self._hash(key)
        d = self.shift[b]
        k = -d - 1 if d < 0 else self._at(x, y, d)
        return k if self.slots[k] == key else -1


class Codec:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.whole = PerfectHash(list(ranks))
        self.slot_id = [-1 if key is None else ranks[key] for key in self.whole.slots]
        self.token = {r: key for key, r in ranks.items()}
        self.number = {r: r for r in self.token}  # one object per id, however many words hold it
        self.byte_id = [ranks.get(bytes([b])) for b in range(256)]
        #: Two ids as one number, to the id of their bytes together.
        self.joined = {x << 20 | y: r for key, r in ranks.items() for k in range(1, len(key)) if (x := ranks.get(key[:k])) is not None and (y := ranks.get(key[k:])) is not None}
        self.find = regex.compile(pattern).findall
        self.known: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Always the lowest rank first, leftmost among equals. Ids name the pieces; a merged-away place holds -1."""
        n, joined = len(piece), self.joined.get
        part = list(map(self.byte_id.__getitem__, piece))
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        wide = n.bit_length()  # an entry is one number: rank and place
        low = (1 << wide) - 1
        heap = [r << wide | k for k in range(n - 1) if (r := joined(part[k] << 20 | part[k + 1])) is not None]
        heapify(heap)
        while heap:
            entry = heappop(heap)
            k, r = entry & low, entry >> wide
            if part[k] < 0 or (j := after[k]) >= n or joined(part[k] << 20 | part[j]) != r:
                continue  # one of the two has changed since
            part[k], part[j] = r, -1
            after[k] = j = after[j]
            if j < n:
                before[j] = k
                if (x := joined(r << 20 | part[j])) is not None:
                    heappush(heap, x << wide | k)
            if (i := before[k]) >= 0 and (x := joined(part[i] << 20 | r)) is not None:
                heappush(heap, x << wide | i)
        return tuple([self.number[p] for p in part if p >= 0])

    def lookup(self, word: str) -> tuple[int, ...]:
        ids = self.older.get(word)
        if ids is None:
            piece = word.encode("utf-8", "surrogatepass")
            slot = self.whole.slot(piece)
            ids = (self.number[self.slot_id[slot]],) if slot >= 0 else self.merge(piece)
        if len(word) <= LONGEST_KNOWN:
            if len(self.known) >= MOST_KNOWN:  # words in use come back from the older half
                self.known, self.older = {}, self.known
            self.known[word] = ids
        return ids

    def encode_into(self, text: str, out: list[int]) -> None:
        known, lookup = self.known, self.lookup
        for word in self.find(text):
            ids = known.get(word)
            if ids is None:
                ids = lookup(word)
                known = self.known
            out += ids

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        self.encode_into(text, out)
        return out

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.token.__getitem__, ids))


def _vocabulary(spark, ranks_path: str):
    """The file's bytes go to each worker once."""
    with open(ranks_path, "rb") as f:
        return spark.sparkContext.broadcast(f.read())


def encode(docs: DataFrame, ranks_path: str, pattern: str, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: its id and `ids`, the token ids of its whole text."""
    raw = _vocabulary(docs.sparkSession, ranks_path)

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        import numpy as np
        import pyarrow as pa

        encoder = worker_cache("byte-level BPE", f"codec {ranks_path} {pattern}", lambda: Codec(parse_ranks(raw.value.splitlines()), pattern))
        for b in batches:
            flat, ends = [], [0]
            for text in b[text_column]:
                encoder.encode_into(text or "", flat)
                ends.append(len(flat))
            ids = pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.array(flat, dtype=np.int32)))
            yield {id_column: b[id_column], "ids": ids}

    return map_texts(docs, [id_column, text_column], kernel, f"{id_column} {docs.schema[id_column].dataType.simpleString()}, ids array<int>")


def decode(encoded: DataFrame, ranks_path: str, id_column: str = "doc_id", ids_column: str = "ids", keep: tuple[str, ...] = ()) -> DataFrame:
    """One row per row of `encoded`: its id, the columns in `keep`, and `decoded`, the bytes that the ids stand for."""
    raw = _vocabulary(encoded.sparkSession, ranks_path)
    names = [id_column, *keep]
    schema = ", ".join(f"{c} {encoded.schema[c].dataType.simpleString()}" for c in names)

    def kernel(batches: Iterator[dict]) -> Iterator[dict]:
        token = worker_cache("byte-level BPE", f"tokens {ranks_path}", lambda: {r: key for key, r in parse_ranks(raw.value.splitlines()).items()}).__getitem__
        for b in batches:
            yield {c: b[c] for c in names} | {"decoded": [b"" if ids is None else b"".join(map(token, ids.tolist())) for ids in b[ids_column]]}

    return map_texts(encoded, [*names, *([ids_column] if ids_column not in names else [])], kernel, f"{schema}, decoded binary")
