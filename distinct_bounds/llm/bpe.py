"""Byte-level BPE: whole pre-tokens through a minimal perfect hash, the others through a heap over linked bytes."""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Sequence
from dataclasses import dataclass, field
from heapq import heapify, heappop, heappush

import numpy as np
import regex
import xxhash
from pyspark.sql import DataFrame

from distinct_bounds.llm.common import col, table, text_udf, with_outputs

VOCABULARY = "byte_bpe_multi_50k.tiktoken"
KINDS = {"ids": "array<int>", "n_tokens": "long", "ids_sha256": "string", "decoded_sha256": "string", "decoded": "binary"}
MASK = (1 << 64) - 1
SPREAD = 0x9E3779B97F4A7C15


# The public pattern of the default vocabulary, and what equals it, by the faster
# standard module, on texts without marks, numbers other than digits, and rare white space.
KNOWN_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
PLAIN_SPLIT = re.compile(r" ?[^\W\d_]+|'(?:[stmd]|re|ve|ll)| ?(?:[^\s\w]|_)+| ?\d+|\s+(?!\S)|\s+").findall
UNPLAIN = re.compile("[^\x00-\x1b\x20-\x84\x86-\xb1\xb4-\xb8\xba\xbb\xbf-\u024f]").search


def place(hashed: int, shift: int, size: int) -> int:
    """Slot of a hash under its bucket's displacement."""
    mixed = ((hashed ^ (shift * SPREAD & MASK)) * 0xC2B2AE3D27D4EB4F) & MASK
    return (mixed >> 20) % size


@dataclass(frozen=True)
class PerfectHash:
    """Slots 0 to n-1 for exactly n byte strings: a displacement for each bucket of about three;
    a negative one names the slot of a bucket with a single string."""

    shifts: list[int]
    owner: list[int]

    @classmethod
    def of(cls, keys: Sequence[bytes]) -> PerfectHash:
        n = len(keys)
        buckets: list[list[tuple[int, int]]] = [[] for _ in range(n // 3 + 1)]
        for i, key in enumerate(keys):
            h = xxhash.xxh3_64_intdigest(key)
            buckets[h % len(buckets)].append((h, i))
        shifts, owner = [0] * len(buckets), [-1] * n
        order = sorted(range(len(buckets)), key=lambda b: -len(buckets[b]))
        for b in order:
            held = buckets[b]
            if len(held) < 2:
                continue
            for shift in range(1, 1 << 40):
                slots = [place(h, shift, n) for h, _ in held]
                if len(set(slots)) == len(slots) and all(owner[s] < 0 for s in slots):
                    break
            shifts[b] = shift
            for s, (_, i) in zip(slots, held, strict=True):
                owner[s] = i
        free = (s for s in range(n) if owner[s] < 0)
        for b in order:
            if len(buckets[b]) == 1:
                s = next(free)
                shifts[b], owner[s] = -s - 1, buckets[b][0][1]
        return cls(shifts, owner)

    def find(self, key: bytes) -> int:
        """Index of the only string that may equal the key; the caller compares them."""
        h = xxhash.xxh3_64_intdigest(key)
        shift = self.shifts[h % len(self.shifts)]
        return self.owner[-shift - 1 if shift < 0 else place(h, shift, len(self.owner))]


@dataclass(frozen=True)
class Vocabulary:
    """Tokens by rank, the pattern of pre-tokens and the hash of whole tokens."""

    tokens: list[bytes]
    pattern: str
    whole: PerfectHash
    pairs: dict[int, int] = field(default_factory=dict, compare=False, repr=False)

    @classmethod
    def read(cls, path: str, pattern: str) -> Vocabulary:
        with open(path, "rb") as lines:
            ranks = {int(rank): base64.b64decode(token) for token, rank in (x.split() for x in lines if x.strip())}
        if sorted(ranks) != list(range(len(ranks))) or not ranks:
            raise ValueError("ranks must run from 0 without a gap")
        tokens = [ranks[i] for i in range(len(ranks))]
        return cls(tokens, pattern, PerfectHash.of(tokens))

    def merges(self) -> dict[int, int]:
        """Rank of the joint token of each two adjacent tokens that have one; made once a worker."""
        if not self.pairs:
            rank = {t: i for i, t in enumerate(self.tokens)}
            for i, token in enumerate(self.tokens):
                for cut in range(1, len(token)):
                    left, right = rank.get(token[:cut]), rank.get(token[cut:])
                    if left is not None and right is not None:
                        self.pairs[left << 32 | right] = i
        return self.pairs


class Encoder(dict):
    """Pre-token to its ids as packed 32-bit numbers. Two generations are remembered, of which the
    older is dropped when the younger is full, so memory stays bounded and frequent ones stay."""

    def __init__(self, vocabulary: Vocabulary, most: int = 250_000):
        self.vocabulary, self.most, self.older = vocabulary, most, {}
        self.rank = {bytes([b]): i for i, t in enumerate(vocabulary.tokens) if len(t) == 1 for b in t}
        self.bytes_ = [self.rank[bytes([b])] for b in range(256)]
        self.pairs = vocabulary.merges()
        self.any_split = regex.compile(vocabulary.pattern).findall
        self.known = vocabulary.pattern == KNOWN_PATTERN

    def __missing__(self, piece: str) -> bytes:
        found = self.older.get(piece)
        if found is None:
            raw = piece.encode("utf-8", "surrogatepass")
            at = self.vocabulary.whole.find(raw)
            ids = [at] if self.vocabulary.tokens[at] == raw else self.merged(raw)
            found = np.array(ids, "<u4").tobytes()
        if len(self) >= self.most:
            self.older = dict(self)
            self.clear()
        self[piece] = found
        return found

    def merged(self, raw: bytes) -> list[int]:
        """Join the adjacent pair of lowest rank, the leftmost of equals, until none has a joint token.

        Tokens are linked by the positions of their first bytes; a heap holds rank and
        position, and entries that a join has made untrue are passed over.
        """
        n, pairs = len(raw), self.pairs.get
        ids = list(map(self.bytes_.__getitem__, raw))
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [r << 40 | i for i, r in enumerate([pairs(a << 32 | b) for a, b in zip(ids, ids[1:])]) if r is not None]
        heapify(heap)
        while heap:
            top = heappop(heap)
            r, i = top >> 40, top & 0xFFFFFFFFFF
            j = after[i]
            if ids[i] < 0 or j >= n or pairs(ids[i] << 32 | ids[j]) != r:
                continue
            ids[i], ids[j], k = r, -1, after[j]
            after[i] = k
            if k < n:
                before[k] = i
                q = pairs(r << 32 | ids[k])
                if q is not None:
                    heappush(heap, q << 40 | i)
            k = before[i]
            if k >= 0:
                q = pairs(ids[k] << 32 | r)
                if q is not None:
                    heappush(heap, q << 40 | k)
        return [x for x in ids if x >= 0]

    def split(self, text: str) -> list[str]:
        return PLAIN_SPLIT(text) if self.known and not UNPLAIN(text) else self.any_split(text)

    def encode(self, text: str | None) -> np.ndarray:
        return np.frombuffer(b"".join(map(self.__getitem__, self.split(text))), "<u4") if text else np.zeros(0, "<u4")


def decode(ids: Sequence[int], vocabulary: Vocabulary) -> bytes:
    return b"".join(map(vocabulary.tokens.__getitem__, ids))


def default_vocabulary() -> Vocabulary:
    import public_tokenizers

    return Vocabulary.read(public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)


_encoders: dict[int, Encoder] = {}


def encode(docs: DataFrame, vocabulary: Vocabulary | None = None, outputs: Sequence[str] = ("ids", "n_tokens"), text_col: str = "text") -> DataFrame:
    """docs with the outputs asked for, of KINDS, from the whole text.

    ids are the ranks of the tokens of each pre-token by itself, without special tokens;
    decoded are the bytes that the ids stand for, the text in UTF-8. A null text counts as
    empty and has no ids. Every row is returned, repeated ones too; an empty table gives an empty
    one. Columns of docs named as the outputs are replaced.
    """
    if unknown := set(outputs) - set(KINDS):
        raise ValueError(f"unknown outputs: {sorted(unknown)}")
    held = docs.sparkSession.sparkContext.broadcast(vocabulary or default_vocabulary())

    def make():
        encoder = _encoders.get(id(held.value))  # a worker serves many tasks
        if encoder is None:
            _encoders.clear()
            encoder = _encoders[id(held.value)] = Encoder(held.value)
        tokens = held.value.tokens
        decimals = [str(i) for i in range(len(tokens))]

        def work(texts):
            made = {x: [] for x in outputs}
            for text in texts:
                packed = encoder.encode(text)
                ids = packed.tolist()
                for x, column in made.items():
                    if x == "ids":
                        column.append(packed.astype(np.int32))
                    elif x == "n_tokens":
                        column.append(len(ids))
                    elif x == "ids_sha256":
                        column.append(hashlib.sha256(",".join(map(decimals.__getitem__, ids)).encode()).hexdigest())
                    else:
                        raw = b"".join(map(tokens.__getitem__, ids))
                        column.append(raw if x == "decoded" else hashlib.sha256(raw).hexdigest())
            return tuple(made[x] for x in outputs)

        return work

    return with_outputs(docs, text_udf(", ".join(f"{x} {KINDS[x]}" for x in outputs), tuple(outputs), make), text_col, tuple(outputs))


DIGESTS = ("n_tokens", "ids_sha256", "decoded_sha256")


def op2_bpe(spark, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 for every document."""
    return encode(table(spark, sf_dir, "documents").select("doc_id", "text"), outputs=DIGESTS).select("doc_id", *DIGESTS)


def encode_stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: doc_id, n_tokens and the digests of the ids and of what they decode to, a row for each copy.
    A null text has no ids; an empty table stays empty."""
    return encode(docs.select(col("doc_id"), col("text")), outputs=DIGESTS).select("doc_id", *DIGESTS)
