import base64
import hashlib
import zlib
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from knnscope.llm import bpe, packing
from tests.llm.conftest import ODD_TEXTS

RANKS_PATH, WORDS_PATH = P.path("byte_bpe_multi_50k.tiktoken"), P.path("word_bpe_49k.json")
RANKS = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS_PATH, "rb"))}
TIKTOKEN = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=RANKS, special_tokens={})
WORDS = Tokenizer.from_file(WORDS_PATH)


def test_perfect_hash_is_minimal_and_perfect():
    keys = list(RANKS)[:5000]
    h = bpe.MinimalPerfectHash(keys)
    assert sorted(h.slots(keys).tolist()) == list(range(len(keys)))


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60))
def test_ids_equal_the_library_and_decode_to_the_text(text):
    own = bpe.codec(RANKS_PATH, P.PATTERN)
    ids = own.encode(text)
    assert ids == TIKTOKEN.encode_ordinary(text)
    assert own.decode(ids) == text.encode()


def test_a_small_memo_changes_nothing():
    own = bpe.BytePairCodec(RANKS, P.PATTERN, memo_limit=3)
    for text in ("the quick brown fox jumps over it", "another zzzqqq text of several words"):
        assert own.encode(text) == TIKTOKEN.encode_ordinary(text)


def test_words_in_use_outlive_a_full_memo():
    own = bpe.BytePairCodec(RANKS, P.PATTERN, memo_limit=40_000)
    merged = []
    own.merge = lambda piece, merge=own.merge: merged.append(piece) or merge(piece)
    name = lambda n: "".join(chr(97 + int(d)) for d in f"{n:05}")
    texts = [" zzqqx " + " ".join(name(20 * i + j) for j in range(20)) for i in range(40)]
    assert [own.encode(t) for t in texts] == [TIKTOKEN.encode_ordinary(t) for t in texts]
    assert own.older and merged.count(b" zzqqx") == 1
    assert own.memo_used <= own.memo_limit // 2


def test_texts_of_a_group_are_looked_up_together():
    own = bpe.BytePairCodec(RANKS, P.PATTERN)
    learnt = []
    own.learn = lambda words, learn=own.learn: learnt.append(words) or learn(words)
    texts = ["it's a d\u00e9j\u00e0 vu\x1c\x85 \u00a0 x\u00b2", "", "\u4e2d\u6587 it's  a\n\n text\u2003 ", " 12a\t"]
    assert [np.frombuffer(p, "<u4").tolist() for p in own.encode_group(texts)] == [TIKTOKEN.encode_ordinary(t) for t in texts]
    assert len(learnt) == 1


def test_plain_texts_are_split_as_by_the_pattern():
    own = bpe.BytePairCodec(RANKS, P.PATTERN)
    assert own.find_plain is not own.find
    chars = [chr(c) for c in range(bpe.PLAIN)]
    for text in ("".join(chars), " ".join(chars), "  ".join(f"a{c}1{c}{c}'s" for c in chars)):
        assert own.find_plain(text) == own.find(text)
    assert bpe.plain_pattern(r"\w+") is None and bpe.plain_pattern(r"(?i:a)|b") is None and bpe.plain_pattern(r"(?=\s)[^\S]") is not None


def test_digests_of_odd_texts(make_docs, spark):
    docs = make_docs(ODD_TEXTS)
    got = {r.doc_id: r for r in bpe.digest_table(docs, RANKS_PATH, P.PATTERN).collect()}
    for i, t in enumerate(ODD_TEXTS):
        ids = TIKTOKEN.encode_ordinary(t or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert bpe.digest_table(docs.limit(0), RANKS_PATH, P.PATTERN).count() == 0
    encoded = bpe.encode_table(docs, RANKS_PATH, P.PATTERN)
    back = {r.doc_id: bytes(r.bytes) for r in bpe.decode_table(encoded, RANKS_PATH, P.PATTERN).collect()}
    assert back == {i: (t or "").encode() for i, t in enumerate(ODD_TEXTS)}


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60))
def test_word_ids_equal_the_library(text):
    got = np.frombuffer(packing.tokenizer(WORDS_PATH).encode_packed(text), "<u4").tolist()
    assert got == WORDS.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("text", ["\u039f\u0394\u039f\u03a3 x", "a \u039b\u039f\u0393\u039f\u03a3", "a<|endoftext|>b <|startoftext|>", "<|ENDOFTEXT|> <|EndOfText|>", "\u03c2 \u03c3"])
def test_word_ids_equal_the_library_as_it_comes(text):
    got = np.frombuffer(packing.tokenizer(WORDS_PATH).encode_packed(text), "<u4").tolist()
    assert got == Tokenizer.from_file(WORDS_PATH).encode(text, add_special_tokens=False).ids


def test_texts_of_a_group_have_the_ids_of_each_and_words_in_use_stay():
    own = packing.WordTokenizer(WORDS_PATH, limit=60_000)
    learnt: Counter = Counter()
    own.learn = lambda words, learn=own.learn: learnt.update(words) or learn(words)
    name = lambda n: "".join(chr(97 + int(d)) for d in f"{n:05}")
    texts = ["zzqqx, " + " ".join(name(20 * i + j) + "." * (j % 2) for j in range(20)) for i in range(40)]
    texts[7:7] = ["", "d\u00e9j\u00e0 VU!", "a\u200bb zzqqx,", "a<|endoftext|>b", "\u4e2d\u6587 na\u00efve's 12"]
    got = [p for at in range(0, len(texts), 3) for p in own.encode_group(texts[at : at + 3])]
    library = Tokenizer.from_file(WORDS_PATH)
    assert [np.frombuffer(p, "<u4").tolist() for p in got] == [library.encode(t, add_special_tokens=False).ids for t in texts]
    assert own.older and learnt["zzqqx,"] == 1 and own.used <= own.limit // 2


def test_what_is_remembered_is_not_gone_through_for_each_group():
    class Older(dict):
        def __iter__(self):
            raise AssertionError("goes through all that is remembered")

    own = packing.WordTokenizer(WORDS_PATH)
    own.older = Older({f"word{i}": b"" for i in range(1_000)})
    texts = ["some words, äußerst seltene; words 12", "more_words (some) straße"]
    assert own.encode_group(texts) == [own.pack(t) for t in texts]


@pytest.mark.parametrize("histogram", [{}, {4096: 3}, {1: 5000}, {2049: 7, 2047: 7}, {i: 9 for i in range(1, 400)}, {1000: 1, 3000: 1}])
def test_plans_use_up_the_histogram(histogram):
    used: Counter = Counter()
    found = packing.plan(histogram).sequences
    for n, content in found:
        assert sum(k * v for k, v in content.items()) <= 4096
        for k, v in content.items():
            used[k] += n * v
    assert used == Counter(histogram)
    tokens = sum(k * v for k, v in histogram.items())
    assert sum(n for n, _ in found) <= max(1, 1.05 * tokens / 4096 + 1) or 2049 in histogram


def lengths(copies):
    """Lengths as of documents: many short, few long, most of them different."""
    rng = np.random.default_rng(3)
    drawn = np.minimum(4095, np.exp(rng.normal(6.2, 1.0, 3000))).astype(int) + 1
    return {int(k): int(v) * copies for k, v in zip(*np.unique(drawn, return_counts=True))}


@pytest.mark.parametrize("copies", [1, 30])
def test_most_sequences_come_from_the_program_and_none_is_wasted(copies):
    histogram = lengths(copies)
    found = packing.plan(histogram)
    plain = sum(n for n, _ in packing.best_fit([], {k: v for k, v in histogram.items() if k < 4096}, 4096)) + histogram.get(4096, 0)
    assert found.by_program > 0.6 * found.total and found.total <= plain
    assert found.total <= 1.002 * sum(k * v for k, v in histogram.items()) / 4096 + 1


def test_the_program_beats_best_fit_where_best_fit_is_wrong():
    # best fit puts two of the longest together, then three of the next; one of each is exactly full
    histogram = {1843: 600, 1229: 600, 1024: 600}
    found = packing.plan(histogram)
    assert (found.total, found.by_program) == (600, 600)
    assert sum(n for n, _ in packing.best_fit([], histogram, 4096)) == 650


def test_knapsack_equals_brute_force():
    rng = np.random.default_rng(4)
    for _ in range(20):
        sizes = np.sort(rng.choice(np.arange(3, 30), 4, replace=False))
        most, profit = rng.integers(1, 4, 4), rng.random(4)
        table = packing.Knapsack(sizes, most, profit, 40)
        every = np.stack(np.meshgrid(*(np.arange(m + 1) for m in most)), -1).reshape(-1, 4)
        assert table.best[40] == pytest.approx((every @ profit)[every @ sizes <= 40].max())
        held = table.content(40)
        assert sum(profit[i] * n for i, n in held.items()) == pytest.approx(table.best[40])
        assert sum(sizes[i] * n for i, n in held.items()) <= 40 and all(n <= most[i] for i, n in held.items())


def test_the_fractional_solution_is_feasible_and_near_the_bound():
    histogram = lengths(5)
    sizes = np.array(sorted(k for k in histogram if k < 4096))
    need = np.array([histogram[int(s)] for s in sizes])
    found = packing.solve_lp(sizes, need, 4096)
    cover = np.zeros(len(sizes))
    for held, x in found.times.items():
        for i, n in held:
            cover[i] += x * n
    assert (cover <= need * (1 + 1e-6)).all() and found.covered > 0.3 and 0 <= found.gap + 1e-9 < 0.01
    assert float(cover @ sizes) / float(need @ sizes) == pytest.approx(found.covered)


def test_packing_is_whole_and_gapless(make_docs, spark):
    texts = [*ODD_TEXTS, *("word " * n for n in (1, 5, 4094, 4095, 4096, 9000, 100, 100, 700))]
    rows = packing.pack(make_docs(texts), WORDS_PATH).toPandas()
    for i, t in enumerate(texts):
        ids = [*WORDS.encode(t or "", add_special_tokens=False).ids, 1]
        own = rows[rows.doc_id == i].sort_values("piece")
        assert own.length.sum() == len(ids) and own.piece.tolist() == list(range(-(-len(ids) // 4096)))
        for r in own.itertuples():
            assert r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes())
    for _, own in rows.groupby("sequence_id"):
        own = own.sort_values("offset")
        assert own.offset.tolist() == [0, *own.length.cumsum().tolist()[:-1]] and own.length.sum() <= 4096
    assert packing.pack(make_docs([]), WORDS_PATH).count() == 0
