"""Packing token sequences: a configuration linear program over the histogram of lengths.

1. Each document is tokenised, ended by id 1 and, only if longer than the capacity, cut into full pieces and a rest.
   The pass numbers the pieces of each length within its partition and is written to the shared folder.
2. The histogram of lengths (at most ``capacity`` numbers, whatever the input) goes to the driver. Multiplicative
   weights solve the fractional covering program over configurations (multisets of lengths that fit one sequence);
   knapsack dynamic programs price them. Its multiples are rounded, and the program is solved again for what that leaves;
   best fit puts the last rest into gaps and new sequences. All work on counts, so their cost doesn't depend on the number of documents.
3. Every piece finds its place by arithmetic: its number among the pieces of its length falls into the range of one
   configuration. The ranges are a table joined by length and block of numbers.

Defined cases: a NULL or empty text is one piece of one token; ids of NULL documents stay NULL; repeated rows are
packed once each; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import bisect
import struct
import zlib
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
import regex
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from knnscope.io import materialize
from knnscope.llm.common import ENTRY_BYTES, groups, map_rows

CAPACITY, END_ID = 4096, 1
#: Pieces of one length that look up their places together.
RANKS = 1 << 11


class WordTokenizer:
    """Ids of a lower-casing tokenizer that never joins across white space, memoised by what stands between white space.

    What is new in a text is encoded together: words of letters only are one pre-token each, whose last token is marked
    as a word's end in the vocabulary, so the ids of many words in one string fall apart again. Words of lower-case ASCII
    letters are as they are for the tokenizer's model, which is then asked itself. A tail of punctuation after a letter or
    digit is a pre-token of its own and is looked up apart.
    """

    #: White space and letters on which Python and the tokenizer may differ; such texts are encoded as a whole.
    BLANKS = "\x1c\x1d\x1e\x1f\x85"
    ODD = regex.compile("[\u180e\u200b\u2060\ufeff\u0130\u0300-\u036f\ud7a4-\uffff]").search
    TAIL = ".,;:!?|*#%&$)]}\"-"

    def __init__(self, path: str, limit: int = 64 << 20):
        from tokenizers import Tokenizer

        self.own = Tokenizer.from_file(path)
        self.model = self.own.model
        # Python lowers a capital sigma at the end of a word otherwise than the tokenizer
        self.whole = ["\u03a3", *self.BLANKS, *(t.content for t in self.own.get_added_tokens_decoder().values())]
        vocabulary = self.own.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        #: Two halves: once the newer one is full, it takes the older one's place, and what is found there moves to the newer.
        self.memo: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.limit, self.used = limit, 0

    def pack(self, text: str) -> bytes:
        self.own.encode_special_tokens = False
        return np.array(self.own.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def pack_word(self, word: str) -> bytes:
        # special strings count as the text has them; what is special only once lower-cased is ordinary
        self.own.encode_special_tokens = True
        return np.array(self.own.encode(word, add_special_tokens=False).ids, "<u4").tobytes()

    def forget(self) -> None:
        self.memo, self.older, self.used = {}, {}, 0

    def learn(self, words: set[str]) -> None:
        memo, tailed = self.memo, []
        letters = {w for w in words if w.isalpha()}
        for w in words - letters:
            core = w.rstrip(self.TAIL)
            if core and core is not w and core.isalpha():
                tailed.append((w, core))
                if core not in memo:
                    letters.add(core)
            else:
                memo[w] = self.pack_word(w)
        plain = [w for w in letters if w.isascii()]
        ids, ends, tokens = [], [], self.model.tokenize
        for w in plain:
            ids += [t.id for t in tokens(w)]
            ends.append(4 * len(ids))
        packed = np.array(ids, "<u4").tobytes()
        memo.update(zip(plain, map(packed.__getitem__, map(slice, [0, *ends], ends))))
        letters = list(letters.difference(plain))
        if letters:
            self.own.encode_special_tokens = True
            (found,) = self.own.encode_batch_fast([" ".join(letters)], add_special_tokens=False)
            ids = np.array(found.ids, "<u4")
            stops = np.flatnonzero(self.ends[ids]) + 1
            if len(stops) == len(letters):
                packed, at = ids.tobytes(), 0
                for w, stop in zip(letters, (4 * stops).tolist()):
                    memo[w] = packed[at:stop]
                    at = stop
            else:
                for w in letters:
                    memo[w] = self.pack_word(w)
        for w, core in tailed:
            tail = w[len(core) :]
            if tail not in memo:
                memo[tail] = self.pack_word(tail)
            memo[w] = memo[core] + memo[tail]

    @staticmethod
    def room(words: set[str]) -> int:
        """At least what the words take in the memo: one with a tail may keep its core as well, a byte becomes at most one token."""
        return ENTRY_BYTES * (2 * len(words) - sum(map(str.isalpha, words))) + 5 * len("".join(words).encode())

    def recall(self, words: set[str]) -> bool:
        """See that the memo holds all of ``words``; False if they are too many, or some may not be looked up word by word."""
        if not (new := words.difference(self.memo)):
            return True
        known = self.older.keys() & new  # looks up the new ones; the set's own method goes through all older ones
        fresh = new - known
        if self.ODD(" ".join(fresh)):  # such words are never memoised, so they come here each time
            return False
        room = self.room(new)
        if self.used + room > self.limit // 2:
            room = self.room(words)
            if room > self.limit // 2:
                return False
            self.older, self.memo, self.used = self.memo, {}, 0
            known = self.older.keys() & words
            fresh = words - known
        self.used += room
        self.memo.update(zip(known, map(self.older.__getitem__, known)))
        if fresh:
            self.learn(fresh)
        return True

    def encode_packed(self, text: str) -> bytes:
        return self.encode_group([text])[0]

    def encode_group(self, texts: list[str]) -> list[bytes]:
        """The packed ids of each text; what is new in them is looked up together."""
        split = [None if any(c in t for c in self.whole) else t.lower().split() for t in texts]
        if not self.recall(set().union(*(words for words in split if words))):
            return [self.pack(texts[0])] if len(texts) == 1 else [self.encode_packed(t) for t in texts]
        of = self.memo.__getitem__
        return [self.pack(t) if words is None else b"".join(map(of, words)) for t, words in zip(texts, split)]


@lru_cache(maxsize=2)
def tokenizer(path: str) -> WordTokenizer:
    """One per Python worker."""
    return WordTokenizer(path)


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, with_ids: bool = False) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32, part, nth``: nth numbers the pieces of one length in one partition."""

    def kernel(batches):
        own, end = tokenizer(path), END_ID.to_bytes(4, "little")
        part, seen = TaskContext.get().partitionId(), {}
        for rows in batches:
            out = {k: [] for k in ("doc_id", "piece", "start", "length", "ids_crc32", "part", "nth")}
            if with_ids:
                out["ids"] = []
            for group in groups(rows):
                for (doc_id, _), packed in zip(group, own.encode_group([text or "" for _, text in group])):
                    packed += end
                    for n, at in enumerate(range(0, len(packed), 4 * capacity)):
                        cut = packed[at : at + 4 * capacity]
                        length = len(cut) // 4
                        nth = seen[length] = seen.get(length, -1) + 1
                        for k, v in zip(out, (doc_id, n, at // 4, length, zlib.crc32(cut), part, nth)):
                            out[k].append(v)
                        if with_ids:
                            out["ids"].append(np.frombuffer(cut, "<u4").tolist())
            yield out
        own.forget()

    schema = "doc_id long, piece int, start long, length long, ids_crc32 long, part int, nth long"
    return map_rows(docs, ["doc_id", "text"], kernel, schema + (", ids array<long>" if with_ids else ""))


class Knapsack:
    """The most profitable content of every capacity, each size at most ``most`` times: one table of a dynamic program.

    Multiplicities are split into powers of two, so that each becomes a few items that are taken or not; the program
    goes through the items, each as one operation on all capacities.
    """

    def __init__(self, sizes: np.ndarray, most: np.ndarray, profit: np.ndarray, capacity: int):
        most = np.minimum(most, capacity // sizes)
        self.item, self.times, part = [], [], 1
        left = most.copy()
        while left.any():
            take = np.minimum(left, part)
            self.item += np.flatnonzero(take).tolist()
            self.times += take[take > 0].tolist()
            left -= take
            part *= 2
        item, times = np.array(self.item), np.array(self.times)
        self.weight = (sizes[item] * times).tolist()
        gains = (profit[item] * times).tolist()
        self.best = best = np.zeros(capacity + 1)
        self.last = np.full((len(item) + 1, capacity + 1), -1, np.int16 if len(item) < 32_000 else np.int32)
        for k, (w, gain) in enumerate(zip(self.weight, gains)):
            row = self.last[k + 1]
            row[:] = self.last[k]
            if w <= capacity:
                with_it = best[:-w] + gain
                better = with_it > best[w:]
                np.copyto(best[w:], with_it, where=better)
                row[w:][better] = k

    def content(self, capacity: int) -> dict[int, int]:
        """Of each size (by its place in ``sizes``) the number in the best content of ``capacity``."""
        found: dict[int, int] = {}
        k = len(self.last) - 1
        while (k := int(self.last[k, capacity])) >= 0:
            found[self.item[k]] = found.get(self.item[k], 0) + self.times[k]
            capacity -= self.weight[k]
        return found


@dataclass
class Fractional:
    """Configurations with their fractional multiples, which cover the share ``covered`` of the need (in tokens) and no
    size more than once. No solution covers all of it with less than ``bound``."""

    times: dict[tuple, float]
    covered: float
    bound: float

    @property
    def value(self) -> float:
        return float(sum(self.times.values()))

    @property
    def gap(self) -> float:
        """By which share of it the solution is dearer, for what it covers, than the bound."""
        return self.value / (self.bound * self.covered) - 1 if self.covered else 0.0


def solve_lp(
    sizes: np.ndarray, need: np.ndarray, capacity: int, rounds: int = 16, rate: float = 4.0, block: int = 128, spare: int = 0,
    seed: int = 5,
) -> Fractional:
    """The configuration program by multiplicative weights: least sum of multiples that covers the need of every size.

    A size's weight falls exponentially with the share of its need that is covered; its price is its weight a piece,
    begun with its length. Pricing is partial: in each round the sizes are dealt anew at random into blocks, and one
    knapsack a block gives, for every size that is behind, the best configuration of the block that holds it. If that leaves at most
    ``spare`` tokens free, it is taken until one of its sizes is as far as it may be by then; so fillers are spread over
    many configurations. Lengths over the value of the knapsack of all sizes solve the dual and give the bound.
    """
    cover, times, rng = np.zeros(len(sizes)), {}, np.random.default_rng(seed)
    for t in range(1, rounds + 1):
        goal = t / rounds
        most = min(1.0, goal + 0.1)
        dealt = rng.permutation(np.flatnonzero(cover < most - 1e-9))
        n_blocks = max(1, len(dealt) // block)
        for k in range(n_blocks):
            own = np.sort(dealt[k::n_blocks])
            # prices differ a little by chance, so that ties are broken in more than one way
            prices = (sizes * np.exp(-rate * (cover - goal)))[own] * (1 + 0.01 * rng.random(len(own)))
            table = Knapsack(sizes[own], need[own], prices, capacity)
            for j in np.flatnonzero(cover[own] < goal - 1e-9)[::-1].tolist():
                i = int(own[j])
                if cover[i] >= goal - 1e-9:
                    continue
                held = table.content(capacity - int(sizes[i]))
                held[j] = min(held.get(j, 0) + 1, int(need[i]))
                idx, n = own[list(held)], np.array(list(held.values()))
                if capacity - int(sizes[idx] @ n) > spare:
                    continue
                share = n / need[idx]
                x = min(float(((most - cover[idx]) / share).min()), (goal - float(cover[i])) / held[j] * float(need[i]))
                if x > 1e-9:
                    cover[idx] += x * share
                    key = tuple(sorted(zip(idx.tolist(), n.tolist())))
                    times[key] = times.get(key, 0.0) + x
    whole = Knapsack(sizes, need, sizes.astype(float), capacity)
    tokens = float(sizes @ need)
    return Fractional(times, float((sizes * need) @ cover) / tokens, tokens / float(whole.best[capacity]))


def round_off(solution: Fractional, sizes: np.ndarray, need: np.ndarray) -> list[tuple[int, dict[int, int]]]:
    """``[(sequences, {length: pieces in each})]``: whole multiples of the fractional solution, taken out of ``need``.

    First every multiple rounded down; then once more each configuration with a fractional part for which all pieces are
    left, those with the greatest part first.
    """
    rows = [(x, np.array([i for i, _ in held]), np.array([c for _, c in held])) for held, x in solution.times.items()]
    found = []
    for x, idx, n in rows:
        if m := min(int(x + 1e-9), int((need[idx] // n).min())):
            need[idx] -= m * n
            found.append((m, dict(zip(sizes[idx].tolist(), n.tolist()))))
    for _, idx, n in sorted(rows, key=lambda r: -(r[0] % 1)):
        if (need[idx] >= n).all():
            need[idx] -= n
            found.append((1, dict(zip(sizes[idx].tolist(), n.tolist()))))
    return found


@dataclass
class Plan:
    """``sequences``: ``[(number, {length: pieces in each})]``. Those of ``by_program`` come from the configuration program."""

    sequences: list[tuple[int, dict[int, int]]]
    by_program: int = 0
    gap: float = 0.0

    @property
    def total(self) -> int:
        return sum(n for n, _ in self.sequences)


def plan(
    histogram: dict[int, int], capacity: int = CAPACITY, passes: int = 3, rounds: int = 16, least: float = 0.02, held: float = 0.5
) -> Plan:
    """Sequences that use up the histogram exactly.

    The program is solved and rounded, then again for what rounding left, until that places less than ``least`` of it
    (in tokens). The share ``held`` of the pieces shorter than a sixteenth of the capacity takes no part: with them best fit,
    longest first, puts the rest into new sequences without gaps. Plain best fit is computed as well, and is the answer in the
    event that it needs fewer sequences.
    """
    whole = {int(k): int(v) for k, v in histogram.items() if v}
    full = whole.pop(capacity, 0)
    placed = [(full, {capacity: 1})] if full else []
    plain = Plan(best_fit(placed, whole, capacity), full)
    short = {k: int(v * held) for k, v in whole.items() if k < capacity // 16}
    left, gap = {k: v - short.get(k, 0) for k, v in whole.items() if v > short.get(k, 0)}, 0.0
    for nth in range(passes):
        if not left:
            break
        sizes = np.array(sorted(left))
        need = np.array([left[s] for s in sizes.tolist()], np.int64)
        before = int(sizes @ need)
        solution = solve_lp(sizes, need, capacity, rounds)
        gap = gap if nth else solution.gap
        placed = placed + round_off(solution, sizes, need)
        left = {int(s): int(c) for s, c in zip(sizes, need) if c}
        if before - int(sizes @ need) < least * before:
            break
    by_program = sum(n for n, _ in placed)
    for k, v in short.items():
        left[k] = left.get(k, 0) + v
    program = Plan(best_fit(placed, {k: v for k, v in left.items() if v}, capacity), by_program, gap)
    return program if program.total <= plain.total else plain


def best_fit(placed: list, left: dict[int, int], capacity: int) -> list[tuple[int, dict[int, int]]]:
    """``placed`` and the pieces of the histogram ``left``, longest first into the least free space, by groups of equal
    sequences: its cost depends on the number of lengths and configurations, not of pieces."""
    by_free: dict[int, list[tuple[int, tuple]]] = {}
    for n, content in placed:
        by_free.setdefault(capacity - sum(s * c for s, c in content.items()), []).append((n, tuple(content.items())))
    keys = sorted(by_free)

    def put(free: int, n: int, content: tuple) -> None:
        if free not in by_free or not by_free[free]:
            by_free[free] = []
            at = bisect.bisect_left(keys, free)
            if at == len(keys) or keys[at] != free:
                keys.insert(at, free)
        by_free[free].append((n, content))

    for size in sorted(left, reverse=True):
        m = left[size]
        while m:
            at = bisect.bisect_left(keys, size)
            while at < len(keys) and not by_free.get(keys[at]):
                keys.pop(at)
            if at == len(keys):
                free, n, content = capacity, m, ()
            else:
                free = keys[at]
                n, content = by_free[free].pop()
            each = min(free // size, m)
            if n * each > m:
                whole = m // each
                if whole < n and content:
                    put(free, n - whole, content)
                n = whole
            m -= n * each
            put(free - each * size, n, (*content, (size, each)))
    found = []
    for entries in by_free.values():
        for n, content in entries:
            total: dict[int, int] = {}
            for size, c in content:
                total[size] = total.get(size, 0) + c
            found.append((n, total))
    return found


def places(plan_: list) -> list[tuple[int, int, int, int, int, int]]:
    """Rows ``length, lo, hi, each, base, at``: pieces lo..hi-1 of this length go, ``each`` to a sequence, from sequence
    ``base`` on, the first at offset ``at``."""
    rows, used, base = [], {}, 0
    for n, content in plan_:
        at = 0
        for size, each in sorted(content.items(), reverse=True):
            lo = used.get(size, 0)
            used[size] = lo + n * each
            rows.append((size, lo, lo + n * each, each, base, at))
            at += size * each
        base += n
    return rows


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32, sequence_id, offset`` of every piece."""
    spark = docs.sparkSession
    cut = materialize(pieces(docs, path, capacity), "pieces")
    counts = cut.groupBy("length", "part").agg((F.max("nth") + 1).alias("n"))
    before = W.partitionBy("length").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    firsts = materialize(
        counts.select("length", "part", "n", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first")), "firsts"
    )
    histogram = {r[0]: r[1] for r in firsts.groupBy("length").agg(F.sum("n")).collect()}  # at most `capacity` rows
    rows = pd.DataFrame(places(plan(histogram, capacity).sequences), columns=["length", "lo", "hi", "each", "base", "at"], dtype="int64")
    # a range is entered in every block of ranks that it meets, so pieces find theirs by equality, and a length with many
    # pieces is many keys; whether the table, whose size the histogram bounds, is broadcast is left to Spark's own limit
    ranges = spark.createDataFrame(rows, "length long, lo long, hi long, each long, base long, at long")
    block = f"explode(sequence(lo div {RANKS}, (hi - 1) div {RANKS})) AS block"
    lookup = ranges.selectExpr("length", "struct(lo, hi, each, base, at) AS range", block)
    lookup = lookup.groupBy("length", "block").agg(F.array_sort(F.collect_list("range")).alias("ranges"))
    ranked = cut.join(firsts.drop("n"), ["length", "part"]).withColumn("rank", F.col("first") + F.col("nth"))
    ranked = ranked.withColumn("block", F.expr(f"rank div {RANKS}"))
    found = ranked.join(lookup, ["length", "block"]).withColumn(
        "r", F.expr("filter(ranges, x -> x.lo <= rank AND rank < x.hi)[0]")
    )
    nth = F.col("rank") - F.col("r.lo")
    return found.select(
        "doc_id", "piece", "start", "length", "ids_crc32",
        (F.col("r.base") + F.floor(nth / F.col("r.each"))).cast("long").alias("sequence_id"),
        (F.col("r.at") + (nth % F.col("r.each")) * F.col("length")).cast("long").alias("offset"),
    )
