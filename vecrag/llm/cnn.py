"""Toxicity: a convolutional text classifier trained in numpy.

A word's embedding is the mean of the vectors its hashed pieces (the word and its character 3- to 5-grams with
border marks) point to, so inflected forms share most of theirs. Filters of several widths run over the word sequence,
each filter's maximum over the whole text is kept, and a logistic layer gives the score. All of it - the table of
hashed embeddings, the filters and the output layer - is trained by backpropagation with Adam over a bounded labelled
sample, from random values but for one column of the table, which starts at the pieces' smoothed log odds (from random
values alone a few dozen labelled texts teach nothing). Longer texts than SAMPLE_CHARS are trained on by WINDOWS windows at hashed places.

Thresholds are calibrated by language on a fold of the sample that is not trained on: each language's cut is the one of
best F1 there. Scores are mapped through one monotone curve so that the common cut lies at `CUT`; a language with enough
rows in the fold gets its own threshold in `Model.thresholds`, others the common one. The language is predicted from the
text; it is no input of a score.

Defined results: null and empty texts and texts without words get the score of the empty sequence; equal texts get
equal scores; whole texts are read, runs of letters over 40 in consecutive words of 40; labels that are null are not
learned from.
"""

from __future__ import annotations

import re
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag.llm import ppm
from vecrag.llm.common import held_out, map_slices, numbered, sampled_ids, sampled_text

BUCKETS, DIM, FILTERS, WIDTHS = 1 << 16, 12, 8, (1, 2, 3)
#: Bounds of the training sample: rows of each label, characters of a row, windows of a longer one.
SAMPLE_ROWS, SAMPLE_CHARS, WINDOWS, SEED = 1500, 30_000, 30, 42
#: One row in FOLD of the sample calibrates thresholds instead of being trained on, where the sample has LEAST_ROWS rows.
FOLD, LEAST_ROWS = 5, 100
#: Score at which the query contract calls a text toxic.
CUT = 0.3
#: A run of letters and digits, in words of up to 40.
WORD = re.compile(r"[^\W_]{1,40}")
#: Lengths of character n-grams.
GRAMS = (3, 4, 5)
#: Words hashed or projected in one step.
AT_ONCE = 20_000
#: Words whose projected vectors a worker remembers before it starts anew.
REMEMBERED = 80_000


#: Odd multiplier of the polynomial hash and the finishing multiplier (fixed values).
_STEP, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xFF51AFD7ED558CCD)
_POWERS = np.cumprod(np.full(64, _STEP, np.uint64))  # a word has 40 letters and 2 border marks


def _bucket(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * _MIX
    return ((h >> np.uint64(40)) % np.uint64(BUCKETS)).astype(np.int32)


def flat_pieces(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of each word's pieces in one array, word by word, and how many pieces each word has.

    Pieces are the word itself and its character n-grams with border marks; a piece's hash is a polynomial in its code
    points, so all words are hashed at once.
    """
    if not words:
        return np.zeros(0, np.int32), np.zeros(0, np.int64)
    if len(words) > AT_ONCE:
        parts = [flat_pieces(words[k : k + AT_ONCE]) for k in range(0, len(words), AT_ONCE)]
        return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    marked = [f"<{w}>" for w in words]
    size = np.array([len(m) for m in marked])
    code = np.frombuffer("".join(marked).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) + np.uint64(1)
    start = np.cumsum(size) - size
    word = np.repeat(np.arange(len(words)), size)
    place = np.arange(len(code)) - start[word]
    whole = np.add.reduceat(code * _POWERS[place], start)
    owners, found = [np.arange(len(words))], [_bucket(whole)]
    for n in GRAMS:
        last = len(code) - n + 1
        if last <= 0:
            continue
        h = np.full(last, n, np.uint64)
        for k in range(n):
            h = h * _STEP + code[k : k + last]
        inside = place[:last] + n <= size[word[:last]]
        owners.append(word[:last][inside])
        found.append(_bucket(h[inside]))
    owner = np.concatenate(owners)
    order = np.argsort(owner, kind="stable")
    return np.concatenate(found)[order], np.bincount(owner, minlength=len(words))


@dataclass
class Model:
    table: np.ndarray  # BUCKETS x DIM
    filters: np.ndarray  # DIM x (sum of WIDTHS * FILTERS)
    bias: np.ndarray
    top: np.ndarray
    top_bias: float
    common: float = 0.5
    thresholds: dict[str, float] = field(default_factory=dict)

    def curve(self, p: np.ndarray) -> np.ndarray:
        """Monotone map of [0, 1] onto itself that takes the common threshold to CUT."""
        c = min(max(self.common, 1e-6), 1 - 1e-6)
        return np.where(p >= c, CUT + (1 - CUT) * (p - c) / (1 - c), CUT * p / c * (1 - 1e-12))


def _layout() -> list[tuple[int, int, slice]]:
    """(width index, offset in the filter, columns) of each block of projected columns."""
    out, at = [], 0
    for k, width in enumerate(WIDTHS):
        for offset in range(width):
            out.append((k, offset, slice(at, at + FILTERS)))
            at += FILTERS
    return out


LAYOUT = _layout()
COLUMNS = sum(WIDTHS) * FILTERS


def _close(conv: np.ndarray, starts: np.ndarray, width: int) -> None:
    """Take out windows that reach over the end of a text's padding into the next text."""
    ends = np.append(starts[1:], len(conv))
    for k in range(1, width):
        conv[ends - k] = -np.inf


class Scorer:
    """Applies a model in one worker; projected word vectors are computed once a distinct word."""

    def __init__(self, model: Model):
        self.model = model
        self._reset()

    def _reset(self) -> None:
        self.row_of: dict[str, int] = {}
        self.rows = np.zeros((1024, COLUMNS), np.float32)

    def _learn(self, words: list[str]) -> None:
        flat, sizes = flat_pieces(words)
        starts = np.cumsum(sizes) - sizes
        mean = np.add.reduceat(self.model.table[flat], starts, axis=0) / sizes[:, None]
        at = len(self.row_of) + 1  # row 0 is the padding word
        while at + len(words) > len(self.rows):
            self.rows = np.vstack([self.rows, np.zeros_like(self.rows)])
        self.rows[at : at + len(words)] = mean @ self.model.filters
        self.row_of.update(zip(words, range(at, at + len(words)), strict=True))

    def logits(self, texts: list[str | None]) -> np.ndarray:
        found = [WORD.findall(t.lower()) if t else [] for t in texts]
        new = list(set().union(*found) - self.row_of.keys()) if found else []
        if len(self.row_of) + len(new) > REMEMBERED:
            self._reset()
            new = list(set().union(*found))
        for k in range(0, len(new), AT_ONCE):
            self._learn(new[k : k + AT_ONCE])
        pad, get = max(WIDTHS), self.row_of.__getitem__
        out = np.empty(len(texts))
        at = 0
        while at < len(texts):
            end, size = at, 0
            while end < len(texts) and (end == at or size + len(found[end]) <= 30_000):
                size += len(found[end]) + pad
                end += 1
            index: list[int] = []
            starts = []
            for words in found[at:end]:
                starts.append(len(index))
                index += map(get, words)
                index += [0] * pad
            out[at:end] = self._forward(np.array(index), np.array(starts))
            at = end
        return out

    def _forward(self, index: np.ndarray, starts: np.ndarray) -> np.ndarray:
        seen = self.rows[index]
        pooled = []
        for k, width in enumerate(WIDTHS):
            conv = np.full((len(index), FILTERS), self.model.bias[k], np.float32)
            for j, offset, cols in LAYOUT:
                if j == k:
                    conv[: len(index) - offset] += seen[offset:, cols]
            _close(conv, starts, width)
            pooled.append(np.maximum(np.maximum.reduceat(conv, starts, axis=0), 0))
        return np.hstack(pooled) @ self.model.top + self.model.top_bias

    def scores(self, texts: list[str | None]) -> np.ndarray:
        return self.model.curve(1 / (1 + np.exp(-np.clip(self.logits(texts), -50, 50))))


class Adam:
    """Adam over named arrays; of those named in `sparse` only the rows given with a gradient move."""

    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.params, self.rate, self.step = params, rate, 0
        self.m, self.v = ({k: np.zeros_like(p) for k, p in params.items()} for _ in range(2))

    def move(self, grads: dict[str, np.ndarray], rows: dict[str, np.ndarray] | None = None) -> None:
        self.step += 1
        for k, g in grads.items():
            at = (rows or {}).get(k, slice(None))
            m = self.m[k][at] = 0.9 * self.m[k][at] + 0.1 * g
            v = self.v[k][at] = 0.999 * self.v[k][at] + 0.001 * g * g
            self.params[k][at] -= self.rate * (m / (1 - 0.9**self.step)) / (np.sqrt(v / (1 - 0.999**self.step)) + 1e-8)


def fit(texts: list[str], labels: np.ndarray, langs: list[str | None] | None = None, steps: int = 150, rate: float = 0.02, batch: int = 32, seed: int = SEED) -> Model:
    """Train on (text, 0/1 label) rows; langs only group the rows of the fold for threshold calibration."""
    rng = np.random.default_rng(seed)
    y = np.asarray(labels, np.float64)
    model = Model(
        rng.normal(0, 0.1, (BUCKETS, DIM)).astype(np.float32), (0.3 * rng.normal(0, 1, (DIM, COLUMNS))).astype(np.float32),
        np.full((len(WIDTHS), FILTERS), -1.0, np.float32), np.full(len(WIDTHS) * FILTERS, 0.1, np.float32), -2.0,
    )
    fold = np.zeros(len(y), bool) if len(y) < LEAST_ROWS else np.arange(len(y)) % FOLD == FOLD - 1
    if not len(y) or y[~fold].min() == y[~fold].max():
        model.top_bias = -4.0 if not len(y) or y.max() == 0 else 4.0
        model.top[:] = 0
        return model
    row_of: dict[str, int] = {}
    docs = [np.array([row_of.setdefault(w, len(row_of)) for w in WORD.findall(t.lower())], np.int32) for t, held in zip(texts, fold, strict=True) if not held]
    flat, sizes = flat_pieces(list(row_of))
    starts = np.append(0, np.cumsum(sizes))
    row_count = len(row_of)
    del row_of
    y_in = y[~fold]
    model.table[:, 0] = _log_odds(docs, flat, starts, y_in)
    for j, _, cols in LAYOUT:
        model.filters[0, cols] = np.linspace(0.5, 1.5, FILTERS) / WIDTHS[j]
    params = {"table": model.table, "filters": model.filters, "bias": model.bias, "top": model.top, "top_bias": np.array([model.top_bias], np.float32)}
    adam = Adam(params, rate)
    weight = np.where(y_in == 1, 0.5 / y_in.mean(), 0.5 / (1 - y_in.mean())).astype(np.float32)
    while adam.step < steps and row_count:
        for part in np.array_split(rng.permutation(len(y_in)), max(1, len(y_in) // batch))[: steps - adam.step]:
            given = [docs[i] for i in part]
            words, index = np.unique(np.concatenate(given), return_inverse=True)
            if not len(words):
                continue
            owner = np.repeat(np.arange(len(words)), sizes[words])
            first = np.append(0, np.cumsum(sizes[words])[:-1])
            pieces = flat[np.arange(len(owner)) + (starts[words] - first)[owner]]
            many = sizes[words, None].astype(np.float32)
            embedded = np.add.reduceat(model.table[pieces], first, axis=0) / many
            ends = np.cumsum([len(d) for d in given])
            grads = _gradients(params | {"embedded": embedded}, np.split(index, ends[:-1]), y_in[part], weight[part])
            up = grads.pop("embedded")
            told = np.flatnonzero(np.abs(up).sum(1))  # words that some filter's maximum came from
            hit = np.isin(owner, told)
            rows, at = np.unique(pieces[hit], return_inverse=True)
            grads["table"] = np.zeros((len(rows), DIM), np.float32)
            np.add.at(grads["table"], at, (up / many)[owner[hit]])
            adam.move(grads, {"table": rows})
    model.top_bias = float(params["top_bias"][0])
    left = fold if fold.any() else ~fold
    _calibrate(model, [t for t, k in zip(texts, left, strict=True) if k], y[left], [x for x, k in zip(langs, left, strict=True) if k] if langs else None)
    return model


def _log_odds(docs: list[np.ndarray], flat: np.ndarray, starts: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Smoothed log odds of a bucket's presence in texts labelled 1 against 0, shrunk where it was seen rarely."""
    hits = np.zeros((2, BUCKETS))
    for words, label in zip(docs, y, strict=True):
        seen = [flat[starts[w] : starts[w + 1]] for w in np.unique(words)]
        if seen:
            hits[int(label), np.unique(np.concatenate(seen))] += 1
    n = np.array([max(1, (y == 0).sum()), max(1, (y == 1).sum())])
    odds = np.log((hits[1] + 0.5) / (n[1] + 1)) - np.log((hits[0] + 0.5) / (n[0] + 1))
    support = hits.sum(0)
    return np.clip(odds, -4, 6) * support / (support + 5)


def _gradients(params: dict, docs: list[np.ndarray], y: np.ndarray, weight: np.ndarray) -> dict:
    pad = max(WIDTHS)
    index = np.concatenate([np.append(d, np.full(pad, -1)) for d in docs])
    starts = np.cumsum([0, *(len(d) + pad for d in docs[:-1])])
    known = np.vstack([params["embedded"], np.zeros_like(params["embedded"][:1])])  # the last row is the padding word
    seen = (known @ params["filters"])[index]
    pooled, where = [], []
    for k, _ in enumerate(WIDTHS):
        conv = np.repeat(params["bias"][k][None, :], len(index), 0)
        for j, offset, cols in LAYOUT:
            if j == k:
                conv[: len(index) - offset] += seen[offset:, cols]
        _close(conv, starts, WIDTHS[k])
        top = np.maximum.reduceat(conv, starts, axis=0)
        at = np.empty(top.shape, np.int64)
        for d, (a, b) in enumerate(zip(starts, [*starts[1:], len(index)], strict=True)):
            at[d] = a + conv[a:b].argmax(0)
        pooled.append(top)
        where.append(at)
    raw = np.hstack(pooled)
    hidden = np.maximum(raw, 0)
    p = 1 / (1 + np.exp(-np.clip(hidden @ params["top"] + params["top_bias"][0], -50, 50)))
    error = (p - y) * weight / len(y)
    back = np.outer(error, params["top"]) * (raw > 0)
    grads = {"top": hidden.T @ error + 1e-4 * params["top"], "top_bias": np.array([error.sum()]), "bias": np.zeros_like(params["bias"]), "filters": 1e-4 * params["filters"]}
    embedded = np.zeros_like(known)
    for k, _ in enumerate(WIDTHS):
        g = back[:, k * FILTERS : (k + 1) * FILTERS]
        grads["bias"][k] = g.sum(0)
        for j, offset, cols in LAYOUT:
            if j == k:
                at = np.minimum(where[k] + offset, len(index) - 1)
                grads["filters"][:, cols] += np.einsum("df,dfe->ef", g, known[index[at]])
                np.add.at(embedded, index[at].ravel(), (g[:, :, None] * params["filters"][:, cols].T[None]).reshape(-1, embedded.shape[1]))
    return grads | {"embedded": embedded[:-1]}


def _best_cut(p: np.ndarray, y: np.ndarray) -> float:
    """Middle of the gap below the score of best F1 (the largest such score on ties)."""
    order = np.argsort(-p, kind="stable")
    hits = np.cumsum(y[order])
    f1 = 2 * hits / (np.arange(1, len(y) + 1) + y.sum())
    f1[:-1][p[order][1:] == p[order][:-1]] = -1
    at = int(f1.argmax())
    below = p[order][at + 1] if at + 1 < len(p) else 0.0
    return float((p[order][at] + below) / 2)


def _calibrate(model: Model, texts: list[str], y: np.ndarray, langs: list[str | None] | None) -> None:
    scorer = Scorer(model)
    logits = np.concatenate([scorer.logits(texts[k : k + 100]) for k in range(0, len(texts), 100)])
    p = 1 / (1 + np.exp(-np.clip(logits, -50, 50)))
    model.common = _best_cut(p, y)
    scores = model.curve(p)
    names = np.array([x or "" for x in langs]) if langs else np.zeros(0)
    for name, n in Counter(names.tolist()).items():
        rows = names == name
        model.thresholds[name] = _best_cut(scores[rows], y[rows]) if name and n >= 50 and 10 <= y[rows].sum() < n else CUT


def train(df: DataFrame, labels: DataFrame, doc_id: str = "doc_id", text: str = "text", label: str = "toxic", rows: int = SAMPLE_ROWS, languages: ppm.Model | None = None) -> Model:
    """Learn from labelled rows that are not held out: at most `rows` of each label, picked by (seed, id) alone.

    With `languages` thresholds are calibrated by predicted language, else there is the common one.
    """
    given = labels.where(~held_out(doc_id) & F.col(label).isin(0, 1)).select(F.col(doc_id).alias("id"), F.col(label).cast("int").alias("label")).distinct()
    counts = {r["label"]: r["n"] for r in given.groupBy("label").agg(F.count("*").alias("n")).collect()}
    share = F.lit(0.0)
    for name, n in counts.items():
        share = F.when(F.col("label") == name, F.lit(min(1.0, 1.2 * rows / n))).otherwise(share)
    picked = given.where(sampled_ids(given, "id", share, SEED))  # at most about 2.4 * rows ids
    body = sampled_text(F.col(text).cast("string"), F.col(doc_id), SAMPLE_CHARS, WINDOWS, SEED)
    texts = df.where(F.col(text).isNotNull()).select(F.col(doc_id).alias("id"), body.alias("text"))
    got = texts.join(F.broadcast(picked), "id").select(F.xxhash64(F.lit(SEED), F.col("id")).alias("h"), "text", "label").collect()
    chosen = []
    for k in (0, 1):
        chosen += sorted(((r["h"] % (1 << 30), r["text"], k) for r in got if r["label"] == k), key=lambda x: (x[0], x[1]))[:rows]
    given = [r[1] for r in chosen]
    langs = None if languages is None else [x for k in range(0, len(given), 100) for x in languages.predict(given[k : k + 100])[0]]
    return fit(given, np.array([r[2] for r in chosen], float), langs)


def score(df: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id and score of every row; the model's size is fixed (BUCKETS x DIM and the filters), so it is broadcast."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    held: dict[str, Scorer] = {}

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        if "it" not in held:
            held["it"] = Scorer(shared.value)
        return pa.RecordBatch.from_arrays([piece.column("key"), pa.array(held["it"].scores(piece.column("text").to_pylist()), pa.float64())], ["key", "score"])

    given = df.select(F.col(doc_id).alias("key"), F.col(text).cast("string").alias("text"))
    return map_slices(given, "text", work, f"key {df.schema[doc_id].dataType.simpleString()}, score double").withColumnRenamed("key", doc_id)


def keep_clean(df: DataFrame, model: Model, languages: ppm.Model | None = None, text: str = "text") -> DataFrame:
    """Rows that score under their predicted language's threshold (CUT where it has none), all columns kept as they are.

    Languages are predicted only for rows whose score lies between the thresholds, where they decide.
    """
    shared = df.sparkSession.sparkContext.broadcast((model, languages))
    given, back = numbered(df)
    at, held = df.columns.index(text), {}

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        model, languages = shared.value
        if "it" not in held:
            held["it"] = Scorer(model)
        texts = piece.column(at).to_pylist()
        scores = held["it"].scores(texts)
        cuts = np.full(len(texts), CUT)
        known = [CUT, *model.thresholds.values()]
        open_rows = np.flatnonzero((scores >= min(known)) & (scores < max(known)))
        if languages is not None and len(open_rows):
            langs, _ = languages.predict([texts[k] for k in open_rows])
            cuts[open_rows] = [model.thresholds.get(x, CUT) for x in langs]
        return piece.filter(pa.array(scores < cuts))

    return back(map_slices(given, f"c{at}", work, given.schema))
