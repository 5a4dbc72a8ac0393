"""Language identification: averaged hashed subword embeddings and a linear softmax, trained by SGD in numpy.

A text is lower-cased; each word stands between marks; its byte n-grams (2 to 5 long) are hashed into ``buckets`` rows
of an embedding matrix, whose average goes through a linear layer. Because all of that is linear, prediction only
needs, per bucket, the product of both matrices, ``buckets`` x languages, which is what is shipped to the workers: its
size depends on parameters and the number of languages, never on the data.

The training sample is bounded: about ``per_language`` documents of each language, those of the smallest hashes of
their ids, each as a whole and as short stretches. A tenth of it is held back to fit the temperature and the
rejection threshold.

Defined cases: a NULL text, or one without a letter, is ``und`` with score 0 and is rejected; without any training row
every text is ``und``; repeated rows repeat; extra columns are ignored; an empty table gives an empty table.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from knnscope.llm.common import crc_fold, cut, map_rows, release

UNKNOWN = "und"
ORDERS = (2, 3, 4, 5)
LETTER = regex.compile(r"\p{L}").search
SCHEMA = "doc_id long, lang_pred string, score double, rejected boolean"


def marked(text: str) -> np.ndarray:
    """The lower-cased UTF-8 bytes, with one blank before, between and after the words."""
    return np.frombuffer((" " + " ".join(text.lower().split()) + " ").encode(), np.uint8)


def grams(data: np.ndarray, buckets: int, block: int = 1 << 18):
    """Buckets of all n-grams, block by block; an n-gram may begin or end at a blank, but doesn't cross one."""
    for at in range(0, len(data), block):
        part = data[at : at + block + max(ORDERS) - 1].astype(np.uint64)
        blank = part == 32
        # how many bytes from here on belong to the word that begins or continues here, its closing blank included
        stop = np.flatnonzero(blank)
        nxt = np.searchsorted(stop, np.arange(len(part)) + 1)
        end = np.append(stop, len(part) - 1)[np.minimum(nxt, len(stop))]
        room = end - np.arange(len(part)) + 1
        code, out = part.copy(), []
        for n in range(2, max(ORDERS) + 1):
            code = (code[:-1] << np.uint64(8)) | part[n - 1 :]
            if n in ORDERS:
                mine = code[: min(block, len(code))]
                with np.errstate(over="ignore"):
                    h = (mine + np.uint64(n)) * np.uint64(0x9E3779B97F4A7C15)
                out.append(((h >> np.uint64(40)) % np.uint64(buckets)).astype(np.int32)[room[: len(mine)] >= n])
        yield np.concatenate(out) if out else np.empty(0, np.int32)


@dataclass
class LanguageModel:
    languages: list[str]
    table: np.ndarray  # buckets x languages
    bias: np.ndarray
    temperature: float = 1.0
    threshold: float = 0.0

    def logits(self, text: str) -> np.ndarray:
        total, n = np.zeros(len(self.languages)), 0
        for part in grams(marked(text), len(self.table)):
            counts = np.bincount(part, minlength=len(self.table)) if len(part) > len(self.table) else None
            total += counts @ self.table if counts is not None else self.table[part].sum(0)
            n += len(part)
        return total / max(1, n) + self.bias

    def predict(self, text: str | None) -> tuple[str, float, bool]:
        if text is None or not self.languages or not LETTER(text):
            return UNKNOWN, 0.0, True
        p = softmax(self.logits(text) / self.temperature)
        best = int(p.argmax())
        return self.languages[best], float(p[best]), bool(p[best] < self.threshold)


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


def train(
    rows: list[tuple[str, str]], buckets: int = 1 << 15, dim: int = 16, epochs: int = 4, rate: float = 4.0,
    rejected_share: float = 0.001, seed: int = 7,
) -> LanguageModel:
    """``rows`` of text and language. Stretches of 1 to 12 words teach short texts as well."""
    rng = np.random.default_rng(seed)
    languages = sorted({lang for _, lang in rows})
    if not languages:
        return LanguageModel([], np.zeros((buckets, 0)), np.zeros(0))
    held = rng.random(len(rows)) < 0.1
    sets = ([], [])
    for out, (text, lang) in zip(held.astype(int), rows):
        words = text.split()
        spans = [text]
        for _ in range(3 if words else 0):
            at, n = int(rng.integers(len(words))), int(rng.integers(1, 13))
            spans.append(" ".join(words[at : at + n]))
        for k, span in enumerate(spans):
            ids = np.concatenate([*grams(marked(span), buckets), np.empty(0, np.int32)])
            if len(ids):
                own, counts = np.unique(ids, return_counts=True)
                sets[out].append((own, (counts / len(ids))[:, None], languages.index(lang), k == 0))
    embed = rng.normal(0, 1 / dim, (buckets, dim))
    out_w, bias = np.zeros((dim, len(languages))), np.zeros(len(languages))
    steps, done = max(1, epochs * len(sets[0])), 0
    for _ in range(epochs):
        for i in rng.permutation(len(sets[0])):
            own, share, y, _ = sets[0][i]
            lr = rate * (1 - done / steps) + 0.01
            hidden = (embed[own] * share).sum(0)
            g = softmax(hidden @ out_w + bias)
            g[y] -= 1
            back = out_w @ g
            out_w -= lr * np.outer(hidden, g)
            bias -= 0.1 * lr * g
            embed[own] -= lr * share * back
            done += 1
    model = LanguageModel(languages, (embed @ out_w).astype(np.float32), bias)
    if check := sets[1] or sets[0]:
        z = np.array([(model.table[own] * share).sum(0) + bias for own, share, _, _ in check])
        y, whole = np.array([c[2] for c in check]), np.array([c[3] for c in check])
        fits = [(-np.log(softmax(z / t)[np.arange(len(y)), y] + 1e-12).mean(), t) for t in np.geomspace(0.05, 5, 40)]
        model.temperature = float(min(fits)[1])
        p = softmax(z / model.temperature).max(1)[whole]
        # rejects that share of whole held-back documents, and only where another answer is nearly as likely
        model.threshold = float(min(0.5, np.quantile(p, rejected_share))) if len(p) else 0.0
    return model


def sample(docs: DataFrame, learn: Column, per_language: int) -> list[tuple[str, str]]:
    """About ``per_language`` rows of each language among those for which ``learn`` holds: those of the smallest hashes of
    their ids. Their number is bound by that share alone, so no row is left out by chance of order."""
    known = docs.filter(learn & F.col("text").isNotNull() & F.col("lang").isNotNull())
    sizes = {r[0]: r[1] for r in known.groupBy("lang").count().collect()}
    if not sizes:
        return []
    share = F.lit(0.0)
    for lang, n in sizes.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1.0, per_language / n))).otherwise(share)
    unit = F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) / float(1 << 20)
    picked = known.filter(unit < share).select("doc_id", "text", "lang")
    return [(r.text, r.lang) for r in sorted(picked.collect(), key=lambda r: (r.doc_id, r.text))]


def fit(docs: DataFrame, learn: Column | None = None, per_language: int = 400) -> LanguageModel:
    """Learn from ``text`` and ``lang`` of the rows for which ``learn`` holds (default: all)."""
    return train(sample(docs, F.lit(True) if learn is None else learn, per_language))


def predict(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """``doc_id, lang_pred, score, rejected`` of every row; reads only id and text."""

    shared = docs.sparkSession.sparkContext.broadcast(model)

    def kernel(batches):
        own = shared.value
        for rows in batches:
            found = [own.predict(text) for _, text in rows]
            yield {
                "doc_id": [r[0] for r in rows], "lang_pred": [x[0] for x in found],
                "score": [x[1] for x in found], "rejected": [x[2] for x in found],
            }

    return map_rows(docs, ["doc_id", "text"], kernel, SCHEMA)


def accepted(docs: DataFrame, model: LanguageModel) -> DataFrame:
    """The rows of ``docs`` that the model doesn't reject, with all their columns and without a join."""
    import pyarrow as pa

    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        own = shared.value
        for batch in batches:
            at = batch.schema.get_field_index("text")
            for part in cut(batch):
                yield part.filter(pa.array([not own.predict(t)[2] for t in part.column(at).to_pylist()], pa.bool_()))
        release()

    return docs.mapInArrow(run, docs.schema)


def not_held_out(folds: int = 4, held: int = 2) -> Column:
    return crc_fold(F.col("doc_id"), folds) != held
