"""Byte-level BPE encoding and decoding with a two-tier lookup.

Tier one: a minimal perfect hash over the vocabulary resolves pre-tokens that are tokens themselves. Tier two: every
other pre-token starts as linked bytes, and a heap yields the adjacent pair of lowest rank (leftmost on ties) until no
pair is in the vocabulary.

Defined cases: NULL and empty texts have no tokens and decode to empty bytes; other columns of the input are ignored,
so extra columns cannot clash; repeated rows give repeated results; an empty table gives an empty table.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
import struct
from functools import lru_cache

import numpy as np
import regex
import xxhash
from pyspark.sql import DataFrame

from knnscope.llm.common import ENTRY_BYTES, GOLDEN, groups, map_rows, mix64

SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


class MinimalPerfectHash:
    """Maps n distinct keys onto 0..n-1: cascaded bit arrays, each of which keeps the keys that collide with no other.

    A key's slot is the number of set bits before its own. Strangers may get any slot, so the caller compares keys.
    """

    def __init__(self, keys: list[bytes], slack: float = 1.6):
        hashes, self.levels, self.bits, self.ranks, before = self.hashes(keys), [], [], [], 0
        if len(np.unique(hashes)) < len(keys):
            raise ValueError("keys must be distinct and their 64-bit hashes too")
        while len(hashes):
            size = max(8, int(slack * len(hashes)))
            at = self._at(hashes, len(self.levels), size)
            alone = np.bincount(at, minlength=size) == 1
            self.levels.append(size)
            self.bits.append(alone)
            self.ranks.append(before + np.cumsum(alone) - 1)
            before += int(alone.sum())
            hashes = hashes[~alone[at]]
        self.n = before

    @staticmethod
    def hashes(keys: list[bytes]) -> np.ndarray:
        return np.fromiter(map(xxhash.xxh3_64_intdigest, keys), np.uint64, len(keys))

    @staticmethod
    def _at(hashes: np.ndarray, level: int, size: int) -> np.ndarray:
        with np.errstate(over="ignore"):
            return (mix64(hashes + np.uint64(level + 1) * GOLDEN) % np.uint64(size)).astype(np.int64)

    def slots(self, keys: list[bytes]) -> np.ndarray:
        hashes = self.hashes(keys)
        found = np.zeros(len(keys), np.int64)
        todo = np.arange(len(keys))
        for level, size in enumerate(self.levels):
            at = self._at(hashes[todo], level, size)
            hit = self.bits[level][at]
            found[todo[hit]] = self.ranks[level][at[hit]]
            todo = todo[~hit]
            if not len(todo):
                break
        return found


#: Texts below this code point are split by Python's ``re``, which knows no properties but takes their members.
PLAIN = 0x250


def plain_pattern(pattern: str) -> str | None:
    """The same pattern with ``\\p{L}``, ``\\p{N}``, ``\\s`` and ``\\S`` spelt out for characters below ``PLAIN``; None if it holds more."""

    def members(escape: str) -> str:
        spans: list[list[int]] = []
        for c in (c for c in range(PLAIN) if regex.match(escape, chr(c))):
            if spans and spans[-1][1] == c - 1:
                spans[-1][1] = c
            else:
                spans.append([c, c])
        return "".join(rf"\u{a:04x}-\u{b:04x}" for a, b in spans)

    out, within, at = [], False, 0
    while at < len(pattern):
        c = pattern[at]
        if c == "\\":
            escape = next((e for e in (r"\p{L}", r"\p{N}", r"\s", r"\S") if pattern.startswith(e, at)), None)
            if escape is None:
                return None
            out.append(members(escape) if within else f"[{members(escape)}]")
            at += len(escape)
            continue
        if c in "[]" and within == (c == "[") or pattern.startswith("(?", at) and not pattern.startswith(("(?!", "(?=", "(?:"), at):
            return None
        within = c == "[" or within and c != "]"
        out.append(c)
        at += 1
    return "".join(out)


class BytePairCodec:
    """Encoder and decoder for one file of ranks (lines of base64 token and rank) and one pre-token pattern.

    What pre-tokens give is kept in a memo of two halves: once the newer half is full, it takes the place of the older,
    and what is found in the older moves to the newer.
    """

    def __init__(self, ranks: dict[bytes, int], pattern: str, memo_limit: int = 64 << 20):
        self.ranks = ranks
        self.find = regex.compile(pattern).findall
        plain = plain_pattern(pattern)
        self.find_plain = re.compile(plain).findall if plain else self.find
        self.foreign = re.compile(f"[^\0-{chr(PLAIN - 1)}]").search
        self.bytes = [ranks.get(bytes([b]), -1) for b in range(256)]
        self.pairs = [ranks.get(bytes([a, b]), -1) for a in range(256) for b in range(256)]
        tokens = list(ranks)
        self.hash = MinimalPerfectHash(tokens)
        slots = self.hash.slots(tokens)
        self.slot_key = [b""] * len(tokens)
        self.slot_id = [0] * len(tokens)
        for token, slot in zip(tokens, slots.tolist()):
            self.slot_key[slot], self.slot_id[slot] = token, ranks[token]
        self.vocabulary = {i: t for t, i in ranks.items()}
        self.tokens = np.full(max(self.vocabulary, default=-1) + 1, None, object)
        for i, t in self.vocabulary.items():
            self.tokens[i] = t
        self.memo: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.memo_limit, self.memo_used = memo_limit, 0

    @classmethod
    def from_file(cls, path: str, pattern: str) -> BytePairCodec:
        with open(path, "rb") as lines:
            pairs = (line.split() for line in lines if line.strip())
            return cls({base64.b64decode(token): int(rank) for token, rank in pairs}, pattern)

    def merge(self, piece: bytes) -> list[int]:
        """The slow tier. A link is the start of the next part; an entry of the heap is rank and start in one number.

        A part's rank is its id, so the entry that joins two parts also says what they become.
        """
        n, get, pairs, ids = len(piece), self.ranks.get, self.pairs, [self.bytes[b] for b in piece]
        rank = [pairs[a << 8 | b] for a, b in zip(piece, piece[1:])]
        rank.append(-1)
        width = n.bit_length()
        heap = [r << width | i for i, r in enumerate(rank) if r >= 0]
        if heap:
            after, before, mask = list(range(1, n + 2)), list(range(-1, n)), (1 << width) - 1
            heapq.heapify(heap)
            pop, push = heapq.heappop, heapq.heappush
            while heap:
                entry = pop(heap)
                i = entry & mask
                joined = entry >> width
                if rank[i] != joined:
                    continue  # outdated
                ids[i] = joined
                j = after[i]
                after[i] = k = after[j]
                ids[j] = rank[j] = -1
                if k < n:
                    before[k] = i
                    rank[i] = r = get(piece[i : after[k]], -1)
                    if r >= 0:
                        push(heap, r << width | i)
                else:
                    rank[i] = -1
                p = before[i]
                if p >= 0:
                    rank[p] = r = get(piece[p:k], -1)
                    if r >= 0:
                        push(heap, r << width | p)
            ids = [i for i in ids if i >= 0]
        return ids

    def forget(self) -> None:
        self.memo, self.older, self.memo_used = {}, {}, 0

    def learn(self, words: list[str]) -> None:
        """Put the ids of new pre-tokens, packed as little-endian 32-bit numbers, into the memo.

        Only ``memo_limit`` bytes outlast a group of texts; the pre-tokens of one group are always held together.
        """
        pieces = [w.encode() for w in words]
        memo, slot_key, slot_id, pack = self.memo, self.slot_key, self.slot_id, struct.pack
        for word, piece, slot in zip(words, pieces, self.hash.slots(pieces).tolist()):
            if slot_key[slot] == piece:
                memo[word] = slot_id[slot].to_bytes(4, "little")
            else:
                ids = self.merge(piece)
                memo[word] = pack(f"<{len(ids)}I", *ids)

    @staticmethod
    def room(words: set[str]) -> int:
        return ENTRY_BYTES * len(words) + 5 * len("".join(words).encode())

    def recall(self, words: set[str]) -> None:
        """See that the memo holds all of ``words``."""
        if not (new := words.difference(self.memo)):
            return
        half = self.memo_limit // 2
        room = self.room(new)
        if self.memo_used + room > half:
            # words of a group that was larger than the memo are not kept
            self.older = self.memo if self.memo_used <= half else {}
            self.memo, self.memo_used = {}, 0
            new = words
            room = self.room(new)
        self.memo_used += room
        if self.older:
            known = new.intersection(self.older)
            self.memo.update(zip(known, map(self.older.__getitem__, known)))
            new = new - known
        if new:
            self.learn(list(new))

    def split(self, text: str) -> list[str]:
        return (self.find if self.foreign(text) else self.find_plain)(text)

    def encode_packed(self, text: str) -> bytes:
        return self.encode_group([text])[0]

    def encode_group(self, texts: list[str]) -> list[bytes]:
        """The packed ids of each text; what is new in them is looked up together."""
        split = [self.split(t) for t in texts]
        self.recall(set().union(*split))
        of = self.memo.__getitem__
        return [b"".join(map(of, words)) for words in split]

    def encode(self, text: str | None) -> list[int]:
        return np.frombuffer(self.encode_packed(text or ""), "<u4").tolist()

    def decode(self, ids) -> bytes:
        """The bytes of an array or list of ids."""
        return b"".join(self.tokens[ids].tolist()) if len(ids) else b""


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> BytePairCodec:
    """One codec per Python worker."""
    return BytePairCodec.from_file(path, pattern)


def encode_table(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id, n_tokens, ids`` (array of long ids) of every text."""

    def kernel(batches):
        own = codec(path, pattern)
        for rows in batches:
            ids = [own.encode(text) for _, text in rows]
            yield {"doc_id": [r[0] for r in rows], "n_tokens": [len(x) for x in ids], "ids": ids}

    return map_rows(docs, ["doc_id", "text"], kernel, "doc_id long, n_tokens long, ids array<long>")


def decode_table(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """``doc_id, bytes`` of a table ``doc_id, ids``; a NULL array decodes to empty bytes."""

    def kernel(batches):
        own = codec(path, pattern)
        for rows in batches:
            yield {"doc_id": [r[0] for r in rows], "bytes": [own.decode(r[1] or ()) for r in rows]}

    return map_rows(encoded, ["doc_id", "ids"], kernel, "doc_id long, bytes binary")


def digest_table(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Per document the number of tokens, and digests of its ids and of what decoding those ids gives. No shuffle."""

    def kernel(batches):
        own = codec(path, pattern)
        sha = hashlib.sha256
        for rows in batches:
            out = {"doc_id": [], "n_tokens": [], "ids_sha256": [], "decoded_sha256": []}
            for group in groups(rows):
                for (doc_id, _), packed in zip(group, own.encode_group([text or "" for _, text in group])):
                    out["doc_id"].append(doc_id)
                    out["n_tokens"].append(len(packed) // 4)
                    out["ids_sha256"].append(sha(packed).hexdigest())
                    out["decoded_sha256"].append(sha(own.decode(np.frombuffer(packed, "<u4"))).hexdigest())
            yield out

    return map_rows(docs, ["doc_id", "text"], kernel, SCHEMA)
