"""Language identification by prediction by partial matching (PPM).

Each language has a variable-order byte context tree: for every context of 0 to ORDER bytes seen in its training
texts, the bytes that followed and how often. A byte's probability in its longest known context is
count / (total + distinct), and the escape to the next shorter context has distinct / (total + distinct); below the
empty context every byte is equally likely. The statistics are frozen after training, so the exact code length of a
text is a sum over its (ORDER+1)-byte grams; each slice prices its distinct grams once and sums them by text.

The predicted language is the one with the shortest code; the score is its posterior under equal priors, its
evidence counted per text as a whole. Defined results: null text or text without a letter is `und` with score 0;
equal code lengths go to the language that sorts first; letters are compared in lower case; whole texts are coded.

A posterior alone calls any long text one of the languages, so a filter also asks for a code of few enough bits a byte:
the limit comes from training texts coded by trees that have not seen them.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import held_out, map_slices, numbered, sampled_ids, sampled_text

ORDER = 3
#: Training rows of a language: a bounded sample of its labelled rows; of texts over SAMPLE_CHARS characters, WINDOWS windows
#: at hashed places.
SAMPLE_ROWS, SAMPLE_CHARS, WINDOWS, SEED = 400, 20_000, 10, 42
#: A text of LEAST_BYTES or more is of none of the languages if its code has over SLACK times the bits a byte that all but
#: one in TAIL of the unseen training texts need.
LEAST_BYTES, SLACK, TAIL = 40, 1.25, 100
LETTER = re.compile(r"[^\W\d_]")
_START = b"\n" * ORDER


def _grams(buffer: np.ndarray, width: int) -> np.ndarray:
    """Integer of the `width` bytes that end at each position from ORDER on."""
    n = len(buffer) - ORDER
    key = np.zeros(n, np.uint32)
    for k in range(width):
        at = ORDER - width + 1 + k
        key = (key << np.uint32(8)) | buffer[at : at + n]
    return key


def _buffer(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """All texts in lower case, ORDER newlines before each, and the first gram of each text."""
    raw = [t.lower().encode("utf-8", "replace") for t in texts]
    sizes = np.array([len(r) for r in raw], np.int64)
    joined = np.frombuffer(b"".join(_START + r for r in raw), np.uint8)
    return joined, np.cumsum(sizes + ORDER) - sizes - ORDER


@dataclass
class ContextTree:
    """Frozen counts of one language: for each order, sorted gram keys with counts, and contexts with totals and distinct bytes."""

    keys: list[np.ndarray]
    counts: list[np.ndarray]
    contexts: list[np.ndarray]
    totals: list[np.ndarray]
    distinct: list[np.ndarray]

    @classmethod
    def fit(cls, texts: list[str]) -> ContextTree:
        buffer, starts = _buffer(texts)
        inside = np.ones(max(0, len(buffer) - ORDER), bool)
        for start in starts:
            inside[max(0, start - ORDER) : start] = False  # the newlines between texts are no text
        out = cls([], [], [], [], [])
        for order in range(ORDER + 1):
            grams = _grams(buffer, order + 1)[inside] if len(buffer) > ORDER else np.zeros(0, np.uint32)
            keys, counts = np.unique(grams, return_counts=True)
            contexts, at = np.unique(keys >> np.uint32(8), return_index=True)
            out.keys.append(keys)
            out.counts.append(counts.astype(np.float64))
            out.contexts.append(contexts)
            out.totals.append(np.add.reduceat(counts, at).astype(np.float64) if len(at) else np.zeros(0))
            out.distinct.append(np.diff(np.append(at, len(keys))).astype(np.float64))
        return out

    def bits(self, grams: np.ndarray) -> np.ndarray:
        """Code length in bits of the last byte of each gram, given the bytes before it."""
        total = np.zeros(len(grams))
        left = np.arange(len(grams))
        for order in range(ORDER, -1, -1):
            if not len(left):
                return total
            mask = np.uint32(0xFFFFFFFF >> 8 * (3 - order))
            gram = grams[left] & mask
            found, at = _find(self.contexts[order], gram >> np.uint32(8))
            hit, k = _find(self.keys[order], gram)
            weight = np.where(found, self.totals[order][at] + self.distinct[order][at], 1.0) if len(self.contexts[order]) else np.ones(len(left))
            if len(self.keys[order]):
                total[left[hit]] -= np.log2(self.counts[order][k[hit]] / weight[hit])
            escaped = found & ~hit
            if escaped.any():
                total[left[escaped]] -= np.log2(self.distinct[order][at[escaped]] / weight[escaped])
            left = left[~hit]
        total[left] += 8.0
        return total


def _find(values: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    if not len(values):
        return np.zeros(len(wanted), bool), np.zeros(len(wanted), np.int64)
    at = np.minimum(np.searchsorted(values, wanted), len(values) - 1)
    return values[at] == wanted, at


def code_lengths(trees: list[ContextTree], texts: list[str]) -> np.ndarray:
    """Bits of each text under each language: an array texts x languages."""
    buffer, starts = _buffer(texts)
    out = np.zeros((len(texts), len(trees)))
    if len(buffer) <= ORDER:
        return out
    grams, at = np.unique(_grams(buffer, ORDER + 1), return_inverse=True)
    ends = np.append(starts[1:] - ORDER, len(buffer) - ORDER)
    for k, tree in enumerate(trees):
        summed = np.concatenate([[0.0], np.cumsum(tree.bits(grams)[at])])
        out[:, k] = summed[ends] - summed[starts]
    return out


@dataclass
class Model:
    languages: list[str]
    trees: list[ContextTree]
    limit: float = 8.0

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray]:
        names, scores, _ = self.judge(texts)
        return names, scores

    def judge(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Language and score of each text, and whether its code is short enough for a text of that language."""
        bits = code_lengths(self.trees, [t or "" for t in texts])
        lettered = np.array([t is not None and bool(LETTER.search(t)) for t in texts], bool)
        if not self.languages:
            return ["und"] * len(texts), np.zeros(len(texts)), np.zeros(len(texts), bool)
        best = np.argmin(np.round(bits, 6), axis=1)
        score = 1 / np.exp2(np.clip(bits.min(axis=1, keepdims=True) - bits, -1000, 0)).sum(axis=1)
        sizes = np.array([len((t or "").encode("utf-8", "replace")) for t in texts])
        usual = (sizes < LEAST_BYTES) | (bits.min(axis=1) <= self.limit * sizes)
        return [self.languages[b] if ok else "und" for b, ok in zip(best, lettered, strict=True)], np.where(lettered, score, 0.0), usual & lettered


def train(df: DataFrame, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", rows: int = SAMPLE_ROWS) -> Model:
    """Learn from text and non-null lang of rows that are not held out, at most `rows` of each language.

    The sample depends on (seed, id) only. Its share of each language comes from that language's count over all
    rows, so what reaches the driver is bounded by rows x languages x SAMPLE_CHARS.
    """
    open_rows = df.where(~held_out(doc_id) & F.col(lang).isNotNull() & F.col(text).isNotNull())
    counts = {r["lang"]: r["n"] for r in open_rows.groupBy(F.col(lang).alias("lang")).agg(F.count("*").alias("n")).collect()}
    share = F.lit(0.0)
    for name, n in sorted(counts.items()):
        share = F.when(F.col(lang) == name, F.lit(min(1.0, 1.25 * rows / n))).otherwise(share)
    sample = open_rows.where(sampled_ids(open_rows, doc_id, share, SEED))
    body = sampled_text(F.col(text).cast("string"), F.col(doc_id), SAMPLE_CHARS, WINDOWS, SEED)
    got: dict[str, list[tuple[int, str]]] = {}
    for r in sample.select(F.xxhash64(F.lit(SEED), F.col(doc_id)).alias("h"), F.col(lang).alias("lang"), body.alias("text")).collect():
        got.setdefault(r["lang"], []).append((r["h"] % (1 << 30), r["text"]))
    names = sorted(got)
    texts = [[t for _, t in sorted(got[n])[:rows]] for n in names]
    return Model(names, [ContextTree.fit(t) for t in texts], usual_bits(texts))


def usual_bits(texts: list[list[str]]) -> float:
    """Bits a byte that a text of one of the languages has at most, but for a share of 1 / TAIL, times SLACK."""
    rates = []
    for own in texts:
        for tree_of, coded in ((own[::2], own[1::2]), (own[1::2], own[::2])):
            long = [t for t in coded if len(t.encode()) >= LEAST_BYTES]
            if tree_of and long:
                rates.append(code_lengths([ContextTree.fit(tree_of)], long)[:, 0] / [len(t.encode()) for t in long])
    return min(8.0, float(np.quantile(np.concatenate(rates), 1 - 1 / TAIL)) * SLACK) if rates else 8.0


def identify(df: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, lang_pred and score of every row; the model's size is bounded by its training sample, so it is broadcast."""
    shared = df.sparkSession.sparkContext.broadcast(model)

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        names, scores = shared.value.predict(piece.column("text").to_pylist())
        return pa.RecordBatch.from_arrays([piece.column("key"), pa.array(names, pa.string()), pa.array(scores, pa.float64())], ["key", "lang_pred", "score"])

    given = df.select(F.col(doc_id).alias("key"), F.col(text).cast("string").alias("text"))
    return map_slices(given, "text", work, f"key {df.schema[doc_id].dataType.simpleString()}, lang_pred string, score double").withColumnRenamed("key", doc_id)


def keep_identified(df: DataFrame, model: Model, least: float = 0.5, text: str = "text") -> DataFrame:
    """Rows whose text has a predicted language with a score of `least` or more and a code of usual length, all columns kept."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    given, back = numbered(df)
    at = df.columns.index(text)

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        langs, scores, usual = shared.value.judge(piece.column(at).to_pylist())
        return piece.filter(pa.array([lang != "und" and score >= least and ok for lang, score, ok in zip(langs, scores, usual.tolist(), strict=True)], pa.bool_()))

    return back(map_slices(given, f"c{at}", work, given.schema))
