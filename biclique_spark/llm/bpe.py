"""Byte-level BPE encoding and decoding with a two-tier lookup.

Tier 1: a minimal perfect hash over the vocabulary resolves a whole pre-token that is itself a token. Tier 2:
other pre-tokens are merged by a heap over a doubly linked list of their bytes, lowest rank first and, of equal
ranks, leftmost first. What was resolved is remembered in a bounded table. Whole texts are read; nothing is shuffled.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import struct
from collections.abc import Iterator

import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biclique_spark.llm.common import lean, parts
from biclique_spark.llm.token_counts import batches, pieces

#: Bytes of the tables of resolved strings, with what an entry takes beside them; pieces looked up at once.
KEPT, ENTRY, PART = 256 << 20, 180, 1 << 14
#: Patterns whose matches never reach over a space that follows a non-space, so pieces() may cut there.
CUTTABLE = (r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+",)
_MASK = (1 << 64) - 1
_SLOTS_A, _SLOTS_B = 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93

_encoders: dict[tuple[str, str], Encoder] = {}


class MinimalPerfectHash:
    """n keys to 0..n-1 without gaps, by hash and displace: keys fall into buckets of about three, and each bucket,
    the largest first, gets the first displacement that sends its keys to free slots; a bucket of one key names its
    slot, as a negative number."""

    def __init__(self, keys: list[bytes]):
        self.n, self.m = len(keys), max(1, len(keys) // 3)
        buckets: list[list[int]] = [[] for _ in range(self.m)]
        hashes = [xxhash.xxh3_64_intdigest(k) for k in keys]
        if len(set(hashes)) != self.n:
            raise ValueError("keys repeat")
        for h in hashes:
            buckets[h % self.m].append(h)
        self.shift, taken = [0] * self.m, bytearray(self.n)
        order = sorted(range(self.m), key=lambda b: -len(buckets[b]))
        for b in order:
            if len(buckets[b]) < 2:
                break
            d = 0
            while True:
                slots = [self._slot(h, d) for h in buckets[b]]
                if len(set(slots)) == len(slots) and not any(taken[s] for s in slots):
                    break
                d += 1
            self.shift[b] = d
            for s in slots:
                taken[s] = 1
        free = (s for s in range(self.n) if not taken[s])
        for b in order:
            if len(buckets[b]) == 1:
                self.shift[b] = -1 - next(free)

    def _slot(self, h: int, d: int) -> int:
        x = ((h >> 20 ^ h) + d * _SLOTS_B) * _SLOTS_A & _MASK
        return ((x ^ x >> 29) * _SLOTS_B & _MASK) * self.n >> 64

    def __call__(self, key: bytes) -> int:
        """The key's place; some place for a string that is no key."""
        h = xxhash.xxh3_64_intdigest(key)
        d = self.shift[h % self.m]
        return -1 - d if d < 0 else self._slot(h, d)


class Encoder:
    """ranks: token bytes to id. pattern: the regular expression of pre-tokens."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.ranks, self.find = ranks, regex.compile(pattern).findall
        self.cuttable = pattern in CUTTABLE
        self.hash = MinimalPerfectHash(list(ranks))
        self.token, self.packed = [b""] * len(ranks), [b""] * len(ranks)
        for t, r in ranks.items():
            s = self.hash(t)
            self.token[s], self.packed[s] = t, struct.pack("<I", r)
        self.bytes_of = dict.fromkeys(range(max(ranks.values(), default=-1) + 1), b"") | {r: t for t, r in ranks.items()}
        self.column = pa.array([self.bytes_of[i] for i in range(len(self.bytes_of))], pa.large_binary())
        self.of_byte = [ranks.get(bytes([x])) for x in range(256)]
        self.of_two = [[ranks.get(bytes([x, y])) for y in range(256)] for x in range(256)]
        # Two generations of each table: what is used again moves to the younger one, the elder is dropped.
        self.of_piece: dict[str, bytes] = {}
        self.of_word: dict[str, bytes] = {}
        self.elder: tuple[dict[str, bytes], dict[str, bytes]] = {}, {}
        self.held = 0

    def word(self, word: str, remember: bool = True) -> bytes:
        """A pre-token's ids as little-endian 32-bit integers; what tier 2 found is remembered."""
        raw = word.encode("utf-8", "surrogatepass")
        s = self.hash(raw)
        if self.token[s] == raw:
            return self.packed[s]
        ids = self.of_word.get(word)
        if ids is None:
            ids = self.elder[1].get(word)
            if ids is None:
                found = self.merged(raw)
                ids = struct.pack(f"<{len(found)}I", *found)
            if remember:
                self.of_word[word] = ids
                self.held += ENTRY + len(word) + len(ids)
        return ids

    def merged(self, raw: bytes) -> list[int]:
        """Tier 2. Parts are named by where they start; end[i] is where part i ends, id_[i] its id (None once it is part of
        another), pair[i] the heap's entry for part i with the next one: rank and start as one number, stale in the heap
        where pair[i] is another. The first of the pairs that a merge makes takes the top's place in the heap."""
        n, rank_of, of_two = len(raw), self.ranks.get, self.of_two
        shift = n.bit_length()
        mask = (1 << shift) - 1
        id_ = [self.of_byte[x] for x in raw]
        end, before = list(range(1, n + 1)), list(range(-1, n - 1))
        pair = [None if (r := of_two[x][y]) is None else r << shift | i for i, (x, y) in enumerate(zip(raw, raw[1:]))]  # noqa: B905
        pair.append(None)
        heap = [x for x in pair if x is not None]
        heapq.heapify(heap)
        while heap:
            top = heap[0]
            i = top & mask
            if pair[i] != top:
                heapq.heappop(heap)
                continue
            j = end[i]
            end[i] = stop = end[j]
            id_[i], id_[j], pair[j], first = top >> shift, None, None, True
            if stop < n:
                before[stop] = i
                if (r := rank_of(raw[i : end[stop]])) is None:
                    pair[i] = None
                else:
                    pair[i] = x = r << shift | i
                    heapq.heapreplace(heap, x)
                    first = False
            else:
                pair[i] = None
            if (p := before[i]) >= 0:
                if (r := rank_of(raw[p:stop])) is None:
                    pair[p] = None
                else:
                    pair[p] = x = r << shift | p
                    if first:
                        heapq.heapreplace(heap, x)
                        first = False
                    else:
                        heapq.heappush(heap, x)
            if first:
                heapq.heappop(heap)
        return [x for x in id_ if x is not None]

    def piece(self, piece: str) -> bytes:
        words = self.find(piece)
        if len(words) == 1:  # remembered as a piece
            return self.word(words[0], False)
        return b"".join(map(self.word, words))

    def encode(self, text: str) -> bytes:
        """All ids of a text. Only pieces that the table doesn't know are matched against the pattern; a long text is
        looked up part by part, so the tables outgrow their bound by one part at most."""
        all_, out = pieces(text) if self.cuttable else [text], []
        for at in range(0, len(all_), PART):
            if self.held > KEPT // 2:
                self.elder, self.of_piece, self.of_word, self.held = (self.of_piece, self.of_word), {}, {}, 0
            part, known = all_[at : at + PART], self.of_piece
            for p in {p for p in part if p not in known}:
                ids = self.elder[0].get(p)
                if ids is None:
                    ids = self.piece(p)
                known[p] = ids
                self.held += ENTRY + len(p) + len(ids)
            out.append(b"".join(map(known.__getitem__, part)))
        return out[0] if len(out) == 1 else b"".join(out)

    def decode(self, ids: bytes) -> pa.Buffer | bytes:
        """The bytes behind little-endian ids: Arrow takes the tokens' column by them, which lays its values end to end."""
        n = len(ids) // 4
        if not n:
            return b""
        _, ends, values = self.column.take(pa.Array.from_buffers(pa.uint32(), n, [None, pa.py_buffer(ids)])).buffers()
        return values[: struct.unpack_from("<q", ends, 8 * n)[0]]


def encoder(path: str, pattern: str) -> Encoder:
    """The encoder of a rank file; one is kept for each Python worker."""
    if (path, pattern) not in _encoders:
        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        _encoders[path, pattern] = Encoder(ranks, pattern)
    return _encoders[path, pattern]


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))


def encode(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids (array of int), n_tokens of each row. Edge cases as in round_trip()."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(path, pattern)
        for b in source:
            start = 0
            for part in batches(b.column(1).to_pylist()):
                ids = [struct.unpack(f"<{len(x) // 4}I", x) for x in map(e.encode, part)]
                out = [b.column(0)[start : start + len(part)], pa.array(ids, pa.list_(pa.int32())), pa.array(map(len, ids), pa.int64())]
                start += len(part)
                yield pa.record_batch(out, ["doc_id", "ids", "n_tokens"])

    return _rows(docs, id_col, text_col).mapInArrow(lean(run), "doc_id long, ids array<int>, n_tokens long")


def decode(encoded: DataFrame, path: str, pattern: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, text of each row of ids; null ids give empty text, bytes that are not UTF-8 the replacement sign."""

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        of = encoder(path, pattern).bytes_of
        for b in source:
            texts = [b"".join(map(of.__getitem__, x or ())).decode("utf-8", "replace") for x in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(lean(run), "doc_id long, text string")


def round_trip(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: each text encoded, and its ids decoded again.

    Null and empty texts have no ids and the digest of nothing. Null ids of rows stay null, repeated rows are
    treated one by one, very long texts are read whole, an empty table gives an empty result and other columns
    are not read; rows are not compared, so there are no ties.
    """

    def run(source: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(path, pattern)
        for b in source:
            n, ids_sha, text_sha = [], [], []
            for t in (t for p in parts(b.column(1)) for t in p.to_pylist()):
                ids = e.encode(t)
                n.append(len(ids) // 4)
                ids_sha.append(hashlib.sha256(ids).hexdigest())
                text_sha.append(hashlib.sha256(e.decode(ids)).hexdigest())
            out = [b.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())]
            yield pa.record_batch(out, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    return _rows(docs, id_col, text_col).mapInArrow(lean(run), schema)
