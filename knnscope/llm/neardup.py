"""Near-duplicate documents: b-bit minwise signatures and a multi-index Hamming join, confirmed on full shingle sets.

Each distinct shingle set gets a signature of ``LANES`` minwise values cut to 16 bits, four to a long. The distance of
two signatures is the number of lanes that differ. The index covers the first ``CHUNKS`` longs: within distance
2 ``CHUNKS`` - 1 of those lanes, some long differs in at most one lane (pigeonhole), so each long is entered four times,
each time without one lane, and equal entries of two documents lead to every such pair. At a Jaccard similarity of 0.85
a lane differs with probability 0.15, so a pair escapes the index with probability 2e-8 (1e-6 at 0.8); those it finds
must also be within ``farthest`` of all lanes, five standard deviations over the mean at the threshold, which rejects
about 2.4e-6 of the pairs there. An odd sketch follows: a bit array in which each shingle flips one bit, so that two sketches
never differ in more bits than the sets in shingles; for sets of up to ``DENSE`` shingles what it rejects is certain, for
larger ones it takes a share of the shingles and a margin of five standard deviations. What remains is compared on full
sets.

Groups of copies never become pairs. Equal sets are one class from the start. Then every bucket of the index links its
members to one of them, the one that shares the most entries with others (its classes' original, as a rule); confirmed
links form components. Only then are pairs that share a bucket but no component enumerated, those between the members
outside a bucket's largest component and all its members, with the distance filter inside the join, so that what comes
out is what the signatures can't tell apart. No link between different components is lost, and links within one don't
matter for the result.

Defined cases: NULL and empty texts and texts without words have an empty set and are linked with nothing; texts of
fewer words than a shingle have the whole sequence as their one shingle; repeated rows of one id count as one document
in components (of several texts of one id the set that is greatest as an array is compared) and repeat in the result; NULL ids are linked with nothing; extra columns are ignored; an empty table
gives an empty table.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from knnscope.components import connected
from knnscope.io import materialize
from knnscope.llm.common import Memo, map_rows, mix64

LANES, CHUNKS = 64, 8
#: The longs that are indexed; a signature has as many again, and then the longs of the odd sketch.
LONGS = [f"s{i}" for i in range(CHUNKS)]
#: Longs of the odd sketch, and how many shingles of a set it takes at most (its share is a power of two).
ODD, DENSE = 16, 512
#: Members of a bucket that one task compares with as many others at a time.
BLOCK = 512
SIGN = ["n", "e", "sign"]
_SEEDS = mix64(np.arange(1, 2 * LANES + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_ODD, _ADD = _SEEDS[:LANES] | np.uint64(1), _SEEDS[LANES:]
_CUT = np.tile(np.array([0x7FFF, 0x7FFF, 0x7FFF, 0x3FFF], np.uint64), LANES // 4)
_MIX = mix64(np.arange(101, 109, dtype=np.uint64)) | np.uint64(1)


def word_hashes() -> Memo:
    return Memo(xxhash.xxh3_64_intdigest, 64 << 20)


def shingle_set(text: bytes | None, words: int, memo: dict) -> np.ndarray:
    """The sorted distinct 64-bit hashes of a text's shingles; words are runs without ASCII blanks, A-Z lower-cased."""
    found = (text or b"").lower().split()
    if not found:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(memo.__getitem__, found), np.uint64, len(found))
    n = max(1, len(h) - words + 1)
    total = np.full(n, np.uint64(min(len(h), words)))
    with np.errstate(over="ignore"):
        for k in range(min(words, len(h))):
            total = mix64(total * _MIX[0] + h[k : k + n])
    return np.unique(total)


def signature(shingles: np.ndarray, block: int = 4096) -> np.ndarray:
    """``LANES`` / 4 longs of four minwise values each, of 15 bits (14 in the highest lane) in lanes of 16."""
    low = np.full(LANES, np.iinfo(np.uint64).max, np.uint64)
    with np.errstate(over="ignore"):
        for at in range(0, len(shingles), block):
            part = shingles[at : at + block]
            low = np.minimum(low, (part[None, :] * _ODD[:, None] + _ADD[:, None]).min(1))
    return ((mix64(low) >> np.uint64(48)) & _CUT).astype("<u2").view("<i8")


def odd_sketch(shingles: np.ndarray) -> tuple[int, np.ndarray]:
    """One over the share of the shingles that is taken, and the bits that they flip, as longs."""
    share = 1
    while share * DENSE < len(shingles):
        share *= 2
    part = shingles[(shingles & np.uint64(share - 1)) == 0]
    bits = 64 * ODD
    odd = np.bincount((part >> np.uint64(64 - bits.bit_length() + 1)).astype(np.int64), minlength=bits) & 1
    return share, np.packbits(odd.astype(np.uint8)).view("<i8")


def signatures(docs: DataFrame, words: int) -> DataFrame:
    """``doc_id, n_shingles, set_hash`` and the longs of the signature."""

    def kernel(batches):
        memo = word_hashes()
        for rows in batches:
            sets = [shingle_set(text, words, memo) for _, text in rows]
            signs = np.stack([signature(s) for s in sets])
            out = {
                "doc_id": [r[0] for r in rows], "n_shingles": [len(s) for s in sets],
                "set_hash": [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in sets],
            }
            odd = [odd_sketch(s) for s in sets]
            out["e"] = [share for share, _ in odd]
            out["sign"] = [a.tobytes() + b.tobytes() for a, (_, b) in zip(signs, odd)]
            yield out | {c: signs[:, i] for i, c in enumerate(LONGS)}

    schema = "doc_id long, n_shingles long, set_hash binary, e long, sign binary, " + ", ".join(f"{c} long" for c in LONGS)
    return map_rows(docs.select("doc_id", F.col("text").cast("binary").alias("text")), ["doc_id", "text"], kernel, schema)


def shingle_sets(docs: DataFrame, words: int) -> DataFrame:
    """``doc_id, hashes``: the full sets."""

    def kernel(batches):
        memo = word_hashes()
        for rows in batches:
            sets = [shingle_set(text, words, memo) for _, text in rows]
            yield {"doc_id": [r[0] for r in rows], "hashes": [s.view(np.int64) for s in sets]}

    return map_rows(
        docs.select("doc_id", F.col("text").cast("binary").alias("text")), ["doc_id", "text"], kernel,
        "doc_id long, hashes array<long>",
    )


def farthest(similar: int) -> int:
    """The greatest distance of signatures to look at: the mean at the threshold and five standard deviations."""
    s = similar / 100
    return round(LANES * (1 - s) + 5 * (LANES * s * (1 - s)) ** 0.5)


def close(a, b, similar: int) -> np.ndarray:
    """Which pairs pass what sets of at least ``similar`` per cent Jaccard similarity must satisfy.

    ``a`` and ``b`` are sizes, shares and signs (rows of longs), of shapes that broadcast. Sizes are compared first, then
    signatures, then odd sketches. Adding the largest value to a lane's difference sets the lane's spare bit unless the
    difference is 0, without a carry.
    """
    (na, ea, sa), (nb, eb, sb) = a, b
    out = (100 * na >= similar * nb) & (100 * nb >= similar * na)
    half = LANES // 4
    apart = np.zeros(out.shape, np.int64)
    for i in range(half):
        apart += np.bitwise_count(((sa[..., i] ^ sb[..., i]) + np.int64(0x3FFF7FFF7FFF7FFF)) & np.int64(0x4000800080008000))
    out &= apart <= farthest(similar)
    flipped = np.zeros(out.shape, np.int64)
    for i in range(half, half + ODD):
        flipped += np.bitwise_count((sa[..., i] ^ sb[..., i]).view(np.uint64))
    most = (100 - similar) * (na + nb) / ((100 + similar) * ea)  # shingles in one set only, of those taken
    return out & ((ea != eb) | (flipped <= most + np.where(ea == 1, 0, 5 * np.sqrt(most) + 5)))


def _signs(column: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(column), "<i8").reshape(len(column), -1)


def confirmed(pairs: DataFrame, sets: DataFrame, similar: int) -> DataFrame:
    """Those of ``pairs(u, v)`` whose full sets are similar enough."""
    left = sets.select(F.col("doc_id").alias("u"), F.col("hashes").alias("hu"))
    right = sets.select(F.col("doc_id").alias("v"), F.col("hashes").alias("hv"))
    both = pairs.join(left, "u").join(right, "v").selectExpr(
        "u", "v", "size(array_intersect(hu, hv)) AS common", "size(hu) + size(hv) AS total"
    )
    return both.filter(f"100 * common >= {similar} * (total - common)").select("u", "v")


def index_entries(reps: DataFrame) -> DataFrame:
    """``key, doc``: four entries for each long of the index, each without one 16-bit lane."""
    keep = [-65536, -4294901761, -281470681743361, 281474976710655]  # all bits but those of one lane
    entries = ", ".join(
        f"xxhash64({4 * i + j}, s{i} & {k}L)" for i in range(CHUNKS) for j, k in enumerate(keep)
    )
    return reps.selectExpr("doc", f"explode(array({entries})) AS key")


def link(docs: DataFrame, words: int = 3, similar: int = 85) -> DataFrame:
    """``doc_id, n_shingles, component_id, kept`` of every document."""
    signed = materialize(signatures(docs, words), "signatures")
    full = signed.filter("n_shingles > 0 AND doc_id IS NOT NULL")
    reps = full.groupBy("set_hash").agg(
        F.min("doc_id").alias("doc"), F.first("n_shingles").alias("n"), *(F.first(c).alias(c) for c in (*SIGN[1:], *LONGS))
    )
    reps = materialize(reps, "representatives")
    entries = index_entries(reps)
    shared = entries.groupBy("key").agg(F.count(F.lit(1)).alias("m")).filter("m > 1")
    buckets = materialize(entries.join(shared, "key"), "buckets")

    # one hub for each bucket: who shares the most entries with others
    weight = buckets.groupBy("doc").agg(F.sum("m").alias("weight"))
    weighed = buckets.join(weight, "doc")
    hubs = weighed.groupBy("key").agg(F.max(F.struct("weight", (-F.col("doc")).alias("doc"))).alias("hub"))
    stars = buckets.join(hubs.select("key", (-F.col("hub.doc")).alias("hub")), "key").filter("doc <> hub")
    stars = stars.select(F.col("hub").alias("u"), F.col("doc").alias("v")).distinct()
    stars = materialize(near(stars, reps, similar), "stars")

    # full sets of the documents in buckets; each is computed once
    members = buckets.select(F.col("doc").alias("doc_id")).distinct()
    texts = docs.select("doc_id", "text").join(members.hint("shuffle_hash"), "doc_id", "left_semi")
    sets = shingle_sets(texts, words).groupBy("doc_id").agg(F.max("hashes").alias("hashes"))
    sets = materialize(sets, "shingle-sets")
    edges = materialize(confirmed(stars, sets, similar), "links")
    found = connected(edges)

    # what shares a bucket, but no component
    names = found.select(F.col("node").alias("doc"), "component")
    named = buckets.join(names, "doc", "left").select("key", "doc", F.coalesce("component", "doc").alias("component"))
    sizes = named.groupBy("key", "component").agg(F.count(F.lit(1)).alias("m"))
    mixed = sizes.groupBy("key").agg(F.max(F.struct("m", "component")).alias("top"), F.count(F.lit(1)).alias("kinds"))
    mixed = mixed.filter("kinds > 1").select("key", F.col("top.component").alias("top"))
    rest = materialize(named.join(mixed, "key"), "mixed-buckets")
    more = leftover(rest, reps, similar, stars)
    more = materialize(confirmed(more, sets, similar), "more-links")
    if not more.isEmpty():
        found = connected(edges.unionByName(more))

    rows = signed.selectExpr("doc_id", "n_shingles", "CASE WHEN doc_id IS NOT NULL THEN set_hash END AS set_hash")
    classes = reps.join(found.select(F.col("node").alias("doc"), "component"), "doc", "left")
    classes = classes.select("set_hash", F.coalesce("component", "doc").alias("component"))
    return rows.join(classes, "set_hash", "left").select(
        "doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"),
        F.coalesce(F.col("doc_id") == F.coalesce("component", "doc_id"), F.lit(True)).alias("kept"),
    )


def one_of_each(docs: DataFrame, words: int = 5, similar: int = 80) -> DataFrame:
    """The rows of ``docs`` without near-duplicates: of each component the document of the smallest id stays."""
    gone = materialize(link(docs, words, similar).filter("NOT kept").select("doc_id").distinct(), "duplicates")
    return docs.join(gone.hint("shuffle_hash"), "doc_id", "left_anti").select(*docs.columns)


def signed_as(reps: DataFrame, name: str, prefix: str = "") -> DataFrame:
    return reps.select(F.col("doc").alias(name), *(F.col(c).alias(prefix + c) for c in SIGN))


def near(pairs: DataFrame, reps: DataFrame, similar: int) -> DataFrame:
    """Those of ``pairs(u, v)`` that sizes, signatures and odd sketches don't rule out."""

    def kernel(batches):
        for rows in batches:
            u, v, na, ea, sa, nb, eb, sb = zip(*rows)
            ok = close((np.array(na), np.array(ea), _signs(sa)), (np.array(nb), np.array(eb), _signs(sb)), similar)
            yield {"u": np.array(u)[ok], "v": np.array(v)[ok]}

    both = pairs.join(signed_as(reps, "u", "a_"), "u").join(signed_as(reps, "v", "b_"), "v")
    columns = ["u", "v", *("a_" + c for c in SIGN), *("b_" + c for c in SIGN)]
    return map_rows(both, columns, kernel, "u long, v long")


def leftover(rest: DataFrame, reps: DataFrame, similar: int, done: DataFrame) -> DataFrame:
    """Pairs ``u < v`` in one bucket and in different components that nothing rules out and that weren't tried.

    Of a bucket, the members outside its largest component (side 0) meet all members (side 1), so a large group of
    copies is only met by the few that it doesn't hold. Both sides of a large bucket are dealt out in blocks; a task
    compares one block of each and emits what is left of the pairs, which are never rows before.
    """
    sizes = rest.groupBy("key").agg(
        F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("mb"),
        F.ceil(F.sum((F.col("component") != F.col("top")).cast("int")) / BLOCK).cast("int").alias("hb"),
    )
    both = "explode(filter(array(CASE WHEN component <> top THEN 0 END, 1), x -> x IS NOT NULL)) AS side"
    dealt = rest.join(sizes, "key").selectExpr("key", "doc", "component", "component = top AS most", "mb", "hb", both)
    dealt = dealt.selectExpr(
        "key", "doc", "component", "most", "side",
        "int(pmod(xxhash64(doc, side), CASE WHEN side = 0 THEN hb ELSE mb END)) AS own",
        "explode(sequence(0, CASE WHEN side = 0 THEN mb - 1 ELSE hb - 1 END)) AS other",
    )
    dealt = dealt.selectExpr(
        "key", "doc", "component", "most", "side",
        "CASE WHEN side = 0 THEN own ELSE other END AS h", "CASE WHEN side = 0 THEN other ELSE own END AS m",
    )
    blocks = dealt.join(signed_as(reps, "doc"), "doc").repartition("key", "h", "m").sortWithinPartitions("key", "h", "m", "side")

    def compare(group: list[tuple]) -> tuple[np.ndarray, np.ndarray] | None:
        cut = next((i for i, r in enumerate(group) if r[3] == 1), len(group))
        homes, members = group[:cut], group[cut:]
        if not homes or not members:
            return None
        _, _, _, _, u, cu, _, na, ea, sa = (np.array(c) if i != 9 else _signs(c) for i, c in enumerate(zip(*homes)))
        _, _, _, _, v, cv, most, nb, eb, sb = (np.array(c) if i != 9 else _signs(c) for i, c in enumerate(zip(*members)))
        ok = (cu[:, None] != cv[None, :]) & (most[None, :] | (u[:, None] < v[None, :]))  # two outside members meet once
        if ok.any():
            ok &= close((na[:, None], ea[:, None], sa[:, None, :]), (nb[None, :], eb[None, :], sb[None, :, :]), similar)
        i, j = np.nonzero(ok)
        return (u[i], v[j]) if len(i) else None

    def kernel(batches):
        group: list[tuple] = []
        for rows in batches:
            found = []
            for r in rows:
                if group and r[:3] != group[0][:3]:
                    found.append(compare(group))
                    group = []
                group.append(r)
            found = [f for f in found if f is not None]
            if found:
                yield {"u": np.concatenate([f[0] for f in found]), "v": np.concatenate([f[1] for f in found])}
        if group and (last := compare(group)) is not None:
            yield {"u": last[0], "v": last[1]}

    columns = ["key", "h", "m", "side", "doc", "component", "most", *SIGN]
    joined = map_rows(blocks, columns, kernel, "u long, v long")
    pairs = joined.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v")).distinct()
    tried = done.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))
    return pairs.join(tried, ["u", "v"], "left_anti")
