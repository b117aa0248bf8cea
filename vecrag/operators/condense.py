"""Condensation of retrieved documents: sentence windows, the best window for a query, its neighbours, new order.

Only retrieved (query, document) pairs are touched. Sentences, windows and window vectors are made once a document;
everything but the dense form of a vector is an expression or a two-phase aggregate.
"""

from __future__ import annotations

import weakref
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag.functions import vector as V
from vecrag.session import checkpointed

WINDOW, OVERLAP, EXT, DIM = 3, 2, 1, 384
#: Tokens of an idf table that is broadcast.
BROADCAST_TOKENS = 1_000_000


# -- the hash embedder -----------------------------------------------------------------------------------------------
def idf_table(docs: DataFrame, text: str = "text") -> DataFrame:
    """(token, idf) over all documents: ln((1 + n) / (1 + df)). Tokens are counted before they are shuffled."""
    n = docs.agg(F.count("*").alias("n"))
    df = docs.select(F.explode(F.array_distinct(V.tokens(text))).alias("token")).groupBy("token").agg(F.count("*").alias("df"))
    return df.join(F.broadcast(n)).select("token", F.log((1 + F.col("n")) / (1 + F.col("df"))).alias("idf"))


def idf_of(idf: DataFrame, *texts: DataFrame) -> DataFrame:
    """Rows of an idf table for the tokens of some texts (one column each) alone: what lies beside them is never looked up."""
    met = [t.select(F.explode(V.tokens(t.columns[0])).alias("token")) for t in texts]
    every = met[0]
    for m in met[1:]:
        every = every.unionByName(m)
    return checkpointed(idf.join(every.distinct(), "token", "left_semi"))


def weights_of(idf: DataFrame, dim: int = DIM) -> DataFrame:
    """(token, bucket, x): where a token falls and its signed weight; md5 is taken once a distinct token.

    The table is broadcast to the terms where it has at most BROADCAST_TOKENS rows (under 64 bytes each); beyond, terms
    and table are shuffled, and AQE splits the partitions of frequent tokens.
    """
    out = idf.select("token", V.bucket(F.col("token"), dim).alias("bucket"), (V.sign(F.col("token")) * F.col("idf")).alias("x"))
    if idf not in _TOKENS:
        _TOKENS[idf] = idf.count()
    return F.broadcast(out) if _TOKENS[idf] <= BROADCAST_TOKENS else out


#: Rows of the idf tables met so far, so that each is counted once.
_TOKENS: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


#: Tokens of an idf table that tasks look up by hash, 20 bytes each.
LOOKUP_TOKENS = 4_000_000


def lookup_of(idf: DataFrame, dim: int = DIM):
    """Broadcast (sorted hashes, buckets, weights) of the tokens of an idf table; None beyond LOOKUP_TOKENS, or where two meet."""
    if dim not in _LOOKUPS.get(idf, {}):
        found = None
        if idf not in _TOKENS:
            _TOKENS[idf] = idf.count()
        if _TOKENS[idf] <= LOOKUP_TOKENS:
            t = idf.select(F.xxhash64("token").alias("h"), V.bucket(F.col("token"), dim).cast("short").alias("bucket"), (V.sign(F.col("token")) * F.col("idf")).alias("x")).toArrow()
            h = t["h"].to_numpy()
            order = np.argsort(h)
            if not (np.diff(h[order]) == 0).any():
                found = idf.sparkSession.sparkContext.broadcast(tuple(c.to_numpy()[order] for c in t.columns))
        _LOOKUPS.setdefault(idf, {})[dim] = found
    return _LOOKUPS[idf][dim]


def looked_up(shared, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets and weights of hashed tokens; unknown ones weigh 0."""
    hashes, buckets, x = shared.value
    if not len(hashes):
        return np.zeros(len(h), int), np.zeros(len(h))
    at = np.minimum(np.searchsorted(hashes, h), len(hashes) - 1)
    return buckets[at].astype(int), np.where(hashes[at] == h, x[at], 0.0)


_LOOKUPS: weakref.WeakKeyDictionary = weakref.WeakKeyDictionary()


def sparse_vectors(owners: DataFrame, keys: list[str], idf: DataFrame, dim: int = DIM, text: str = "text") -> DataFrame:
    """(keys, bucket, w): unit-length signed hash vectors of each owner's text, as sparse rows; tokens without idf weigh 0.

    One shuffle by owner: the terms of an owner meet once, for the sums of its buckets and for its length.
    """
    terms = owners.select(*keys, F.explode(V.tokens(text)).alias("token")).join(weights_of(idf, dim), "token")
    summed = terms.select(*keys, "bucket", "x").repartition(*keys).groupBy(*keys, "bucket").agg(F.sum("x").alias("w"))
    length = F.sqrt(F.sum(F.col("w") * F.col("w")).over(W.partitionBy(*keys)))
    return summed.withColumn("len", length).where("len > 0").select(*keys, "bucket", (F.col("w") / F.col("len")).alias("w"))


def packed_vectors(sparse: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, _b, _w): the sparse rows of an owner as two lists, of buckets and of weights."""
    return sparse.groupBy(*keys).agg(F.collect_list("bucket").alias("_b"), F.collect_list("w").alias("_w"))


def packed_owners(owners: DataFrame, key: str, idf: DataFrame, dim: int = DIM, text: str = "text", ids: DataFrame | None = None) -> DataFrame:
    """(key, _b, _w): the same as `packed_vectors` of `sparse_vectors`, without a shuffle of terms: those of an owner follow each
    other in its task, where their weights are looked up. An idf table without a lookup, or keys that come twice, take the shuffle.

    `ids` has one column that comes once exactly where the keys do, if that is cheaper to look at.
    """
    shared = lookup_of(idf, dim)
    ids = owners.select(key) if ids is None else ids
    if shared is None or not ids.groupBy(ids.columns[0]).count().where("count > 1").isEmpty():
        return packed_vectors(sparse_vectors(owners, [key], idf, dim, text), [key])
    rows = owners.select(key, F.monotonically_increasing_id().alias("_row"), text)  # numbered before their terms come apart
    terms = rows.select(key, "_row", F.explode(V.tokens(text)).alias("token")).select("_row", F.xxhash64("token").alias("h"), key)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _runs(batches):
            first = np.flatnonzero(np.diff(t["_row"].to_numpy(), prepend=-1))
            place = np.repeat(np.arange(len(first)), np.diff(first, append=t.num_rows))
            bucket, x = looked_up(shared, t["h"].to_numpy())
            sums = np.bincount(place * dim + bucket, x, len(first) * dim).reshape(-1, dim)
            length = np.sqrt((sums**2).sum(1))
            kept = length > 0
            unit = sums[kept] / length[kept, None]
            r, b = np.nonzero(unit)
            ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(r, minlength=len(unit)))]).astype(np.int32))
            lists = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (b.astype(np.int32), unit[r, b])]
            yield pa.RecordBatch.from_arrays([t[key].combine_chunks().take(pa.array(first[kept])), *lists], [key, "_b", "_w"])

    return terms.mapInArrow(pack, f"{key} {owners.schema[key].dataType.simpleString()}, _b array<int>, _w array<double>")


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Batches cut anew, so that the rows of an owner (`_row`, in rising order) are in one table."""
    held: list[pa.RecordBatch] = []
    last = -1
    for batch in batches:
        if not batch.num_rows:
            continue
        row = batch.column("_row").to_numpy()
        if row[0] < last or (np.diff(row) < 0).any():
            raise ValueError("terms of an owner must follow each other")
        last = row[-1]
        cut = int(np.searchsorted(row, last))
        if cut or (held and held[-1].column("_row")[-1].as_py() != row[0]):
            yield pa.Table.from_batches([*held, batch.slice(0, cut)])
            held = []
        held.append(batch.slice(cut))
    if held:
        yield pa.Table.from_batches(held)


def dense_vectors(sparse: DataFrame, keys: list[str], dim: int = DIM) -> DataFrame:
    """(keys, v): the sparse rows as arrays, for the vector index; scattered in Arrow batches, not looked up per bucket."""
    return dense_of(packed_vectors(sparse, keys), keys, dim)


def dense_of(lists: DataFrame, keys: list[str], dim: int = DIM) -> DataFrame:
    """(keys, v) of packed vectors."""
    kinds = ", ".join(f"{k} {lists.schema[k].dataType.simpleString()}" for k in keys)

    def scatter(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                b, w = part.column("_b"), part.column("_w")
                rows = np.repeat(np.arange(part.num_rows), np.diff(b.offsets.to_numpy()))
                dense = np.zeros((part.num_rows, dim))
                dense[rows, b.flatten().to_numpy()] = w.flatten().to_numpy()
                v = pa.ListArray.from_arrays(pa.array(np.arange(0, dense.size + 1, dim, dtype=np.int32)), pa.array(dense.ravel()))
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in keys), v], [*keys, "v"])

    return lists.mapInArrow(scatter, f"{kinds}, v array<double>")


# -- steps -------------------------------------------------------------------------------------------------------------
def split_sentences(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    return docs.select(F.col(doc_id).alias("doc_id"), V.sentences(text).alias("sents"))


def window_starts(n: Column, window: int, step: int) -> Column:
    """First sentences (from 1) of the windows of n sentences; a last window is aligned to the end."""
    regular = F.sequence(F.lit(1), n - window + 1, F.lit(step))
    last = n - window + 1
    aligned = F.when(F.element_at(regular, -1) < last, F.concat(regular, F.array(last))).otherwise(regular)
    return F.when(n <= 0, F.array().cast("array<int>")).when(n <= window, F.array(F.lit(1))).otherwise(aligned)


def windows(sents: DataFrame, window: int = WINDOW, overlap: int = OVERLAP, step: int | None = None) -> DataFrame:
    """(doc_id, start, stop, text): sliding windows of sentences, `stop` included."""
    step = window - overlap if step is None else step
    if window < 1 or step < 1:
        raise ValueError("a window must have sentences and move forward")
    n = F.size("sents")
    rows = sents.select("doc_id", "sents", F.explode(window_starts(n, window, step)).alias("start"))
    stop = F.least(F.col("start") + window - 1, F.size("sents"))
    return rows.select("doc_id", "start", stop.alias("stop"), F.array_join(F.slice("sents", F.col("start"), F.lit(window)), " ").alias("text"))


def score_windows(wins: DataFrame, pairs: DataFrame, queries: DataFrame, idf: DataFrame, dim: int = DIM) -> DataFrame:
    """(qid, doc_id, start, stop, score): cosine of every window of a paired document with the query.

    A left join keeps windows that share no bucket with the query, with score 0.
    """
    wv = sparse_vectors(wins, ["doc_id", "start"], idf, dim)
    qv = sparse_vectors(queries, ["qid"], idf, dim, "query")
    hits = pairs.select("qid", "doc_id").join(qv.withColumnRenamed("w", "qw"), "qid").join(wv, ["doc_id", "bucket"]).groupBy("qid", "doc_id", "start").agg(F.sum(F.col("qw") * F.col("w")).alias("score"))
    every = pairs.select("qid", "doc_id").join(wins.select("doc_id", "start", "stop"), "doc_id")
    return every.join(hits, ["qid", "doc_id", "start"], "left").select("qid", "doc_id", "start", "stop", F.round(F.coalesce("score", F.lit(0.0)), 6).alias("score"))


#: Queries of a document that one row holds, and first sentences of windows that are scored in one step.
ASKED, STEP = 512, 4096


def best_windows(docs: DataFrame, pairs: DataFrame, queries: DataFrame, idf: DataFrame, cells, n: int = 1, dim: int = DIM) -> DataFrame:
    """(window, overlap, qid, doc_id, start, stop, score): the n best windows of each pair and (window, overlap) cell, as
    `best_window` of `score_windows` gives them.

    Texts meet their queries once; a window is the sum of its sentences, whose terms are looked up where the text is.
    """
    cells = [(int(w), int(o)) for w, o in cells]
    if any(w < 1 or w - o < 1 for w, o in cells):
        raise ValueError("a window must have sentences and move forward")
    qv = packed_owners(queries, "qid", idf, dim, "query")
    met = pairs.select("qid", "doc_id").distinct()
    parts = met.groupBy("doc_id").agg(F.ceil(F.count("*") / ASKED).alias("_n"))
    dealt = met.join(parts, "doc_id").withColumn("_part", F.pmod(F.xxhash64("qid"), F.col("_n"))).join(qv, "qid", "left")
    asked = dealt.groupBy("doc_id", "_part").agg(F.collect_list(F.struct("qid", "_b", "_w")).alias("asked"))
    sents = docs.join(asked, "doc_id").select(F.monotonically_increasing_id().alias("_row"), "doc_id", "asked", V.sentences("text").alias("sents")).where("size(sents) > 0")
    each = F.flatten(F.transform("sents", lambda s, i: F.transform(F.concat(F.array(F.lit("")), V.tokens(s)), lambda t: F.struct(i.alias("no"), t.alias("token")))))
    terms = sents.select("_row", "doc_id", "asked", F.posexplode(each).alias("_pos", "t")).select("_row", "doc_id", F.when(F.col("_pos") == 0, F.col("asked")).alias("asked"), F.col("t.no").alias("no"), F.col("t.token").alias("token"))
    shared, widest = lookup_of(idf, dim), max(w for w, _ in cells)
    if shared is None:  # the join deals terms by token
        rows = terms.join(weights_of(idf, dim), "token", "left").select("_row", "no", F.coalesce("bucket", F.lit(0)).alias("bucket"), F.coalesce("x", F.lit(0.0)).alias("x"), "doc_id", "asked")
        rows = rows.repartition("_row").sortWithinPartitions("_row", "no")
    else:
        rows = terms.select("_row", "no", F.xxhash64("token").alias("h"), "doc_id", "asked")

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _runs(batches):
            first = np.flatnonzero(np.diff(t["_row"].to_numpy(), prepend=-1))
            no, docs_met = t["no"].to_numpy().astype(int), t["doc_id"].to_numpy()
            bucket, x = (t["bucket"].to_numpy(), t["x"].to_numpy()) if shared is None else looked_up(shared, t["h"].to_numpy())
            out: list[tuple] = []
            held_by = t["asked"].combine_chunks()
            if isinstance(held_by, pa.ChunkedArray):
                held_by = held_by.chunk(0)
            filled = np.flatnonzero(held_by.is_valid().to_numpy(zero_copy_only=False))  # one row of each document
            for at, end in zip(first.tolist(), [*first[1:].tolist(), t.num_rows], strict=True):
                doc_id, lists = docs_met[at], held_by[int(filled[np.searchsorted(filled, at)])].values
                count = int(no[end - 1]) + 1
                qids = lists.field("qid").to_numpy()
                q = np.zeros((len(qids), dim))
                b, w = lists.field("_b"), lists.field("_w")
                q[np.repeat(np.arange(len(qids)), b.value_lengths().fill_null(0).to_numpy()), b.flatten().to_numpy()] = w.flatten().to_numpy()
                held: dict[tuple[int, int], list] = {cell: [] for cell in cells}
                for low in range(0, count, STEP):  # windows that start in low..low + STEP - 1
                    high = min(count, low + STEP + widest - 1)
                    rows = slice(at + int(np.searchsorted(no[at:end], low)), at + int(np.searchsorted(no[at:end], high)))
                    body = np.bincount((no[rows] - low) * dim + bucket[rows], x[rows], (high - low) * dim).reshape(-1, dim)
                    for window in sorted({w for w, _ in cells}):
                        many = min(STEP, max(1, count - window + 1) - low)
                        if many < 1:
                            continue
                        sums = sum(body[k : k + many] for k in range(min(window, count)))
                        length = np.sqrt((sums**2).sum(1))
                        made = np.round((q @ sums.T) / np.where(length > 0, length, 1.0), 6) + 0.0
                        for cell in [c for c in cells if c[0] == window]:
                            starts = low + np.arange(many)
                            here = np.flatnonzero((starts % (window - cell[1]) == 0) | (starts == max(0, count - window)))
                            best = here[np.argsort(-made[:, here], axis=1, kind="stable")[:, :n]]
                            held[cell].append((made[np.arange(len(qids))[:, None], best], low + best))
                for (window, overlap), found in held.items():
                    scores, starts = (np.concatenate(v, axis=1) for v in zip(*found, strict=True))
                    best = np.argsort(-scores, axis=1, kind="stable")[:, :n]
                    r, c = np.repeat(np.arange(len(qids)), best.shape[1]), best.ravel()
                    start = starts[r, c]
                    out.append((np.full(len(r), window), np.full(len(r), overlap), qids[r], np.full(len(r), doc_id), start + 1, np.minimum(start + window, count), scores[r, c]))
            if out:
                kinds = (np.int32, np.int32, np.int64, np.int64, np.int32, np.int32, float)
                cols = [pa.array(np.concatenate(c).astype(k)) for c, k in zip(zip(*out, strict=True), kinds, strict=True)]
                yield pa.RecordBatch.from_arrays(cols, ["window", "overlap", "qid", "doc_id", "start", "stop", "score"])

    return rows.mapInArrow(score, "window int, overlap int, qid long, doc_id long, start int, stop int, score double")


def best_window(scored: DataFrame, n: int = 1) -> DataFrame:
    """The n best windows of each (query, document), the earliest on ties."""
    if n == 1:
        best = scored.groupBy("qid", "doc_id").agg(F.min(F.struct((-F.col("score")).alias("low"), "start", "stop")).alias("b"))
        return best.select("qid", "doc_id", "b.start", "b.stop", (-F.col("b.low") + F.lit(0.0)).alias("score"))
    order = W.partitionBy("qid", "doc_id").orderBy(F.desc("score"), "start")
    return scored.withColumn("r", F.row_number().over(order)).where(F.col("r") <= n).drop("r")


def extend(best: DataFrame, sents: DataFrame, ext: int = EXT) -> DataFrame:
    """(.., parts): `ext` sentences on each side, clipped; parts are (part, sentence_no, text) in text order.

    With several windows of a document their sentences are united, each once.
    """
    joined = best.join(sents, "doc_id")
    low, high = F.greatest(F.lit(1), F.col("start") - ext), F.least(F.size("sents"), F.col("stop") + ext)
    ranged = joined.withColumn("no", F.sequence(low, high))
    part = lambda k: F.when(k < F.col("start"), "before").when(k > F.col("stop"), "after").otherwise("core")
    made = ranged.withColumn("parts", F.transform("no", lambda k: F.struct(part(k).alias("part"), k.alias("sentence_no"), F.get("sents", k - 1).alias("text"))))
    one = made.groupBy("qid", "doc_id").agg(F.max("score").alias("score"), F.min("start").alias("start"), F.max("stop").alias("stop"), F.flatten(F.collect_list("parts")).alias("all"))
    numbers = F.array_sort(F.array_distinct(F.transform("all", lambda p: p["sentence_no"])))
    core = lambda k: F.filter("all", lambda p: p["sentence_no"] == k)
    pick = lambda k: F.coalesce(F.get(F.filter(core(k), lambda p: p["part"] == "core"), F.lit(0)), F.get(core(k), F.lit(0)))
    return one.select("qid", "doc_id", "score", "start", "stop", F.transform(numbers, pick).alias("parts"))


def merge(parts: Column) -> Column:
    """Condensed text of the parts."""
    return F.array_join(F.transform(parts, lambda p: p["text"]), " ")


def reorder(condensed: DataFrame) -> DataFrame:
    """(.., new_rank): by best score falling, then retrieval rank, then id; the old rank stays."""
    return condensed.withColumn("new_rank", F.row_number().over(W.partitionBy("qid").orderBy(F.desc("score"), "rank", "doc_id")))


def condense(retrieved: DataFrame, docs: DataFrame, queries: DataFrame, idf: DataFrame, window: int = WINDOW, overlap: int = OVERLAP, ext: int = EXT, dim: int = DIM, by_score: bool = True, n: int = 1, short_as_is: bool = False) -> DataFrame:
    """(qid, doc_id, rank, new_rank, score, start, stop, text, parts) of retrieved (qid, doc_id, rank) pairs.

    Every retrieved document stays: one without sentences keeps its text as it is. short_as_is leaves documents of
    fewer than window + 2 ext sentences unchanged.
    """
    retrieved = checkpointed(retrieved.select("qid", "doc_id", "rank"))  # k rows a query, met three times below
    best = best_windows(docs, retrieved, queries, idf, [(window, overlap)], n, dim).drop("window", "overlap")
    out = extended(retrieved, best, docs, ext)
    keep = F.col("parts").isNull() | (F.col("n_sents") < window + 2 * ext if short_as_is else F.lit(False))
    out = out.withColumn("text", F.when(keep, F.col("whole")).otherwise(merge(F.col("parts")))).withColumn("score", F.coalesce("score", F.lit(0.0)))
    out = reorder(out) if by_score else out.withColumn("new_rank", F.col("rank"))
    return out.select("qid", "doc_id", "rank", "new_rank", "score", "start", "stop", "text", "parts")


def extended(retrieved: DataFrame, best: DataFrame, docs: DataFrame, ext: int) -> DataFrame:
    """(retrieved.., score, start, stop, parts, whole, n_sents): as `extend`, for pairs without windows too; the text of a
    document (or its `sents` and `whole`) meets its pairs once.
    """
    per = best.groupBy("qid", "doc_id").agg(F.max("score").alias("score"), F.min("start").alias("start"), F.max("stop").alias("stop"), F.array_sort(F.collect_list(F.struct("start", "stop"))).alias("_w"))
    both = retrieved.join(per, ["qid", "doc_id"], "left")
    if "sents" in docs.columns:
        both = both.join(docs, "doc_id")
    else:
        both = both.join(docs.select("doc_id", "text"), "doc_id").withColumn("sents", V.sentences("text")).withColumn("whole", F.coalesce("text", F.lit(""))).drop("text")
    n = F.size("sents")
    inside = lambda k: F.exists("_w", lambda w: (k >= w["start"]) & (k <= w["stop"]))
    reach = F.transform("_w", lambda w: F.sequence(F.greatest(F.lit(1), w["start"] - ext), F.least(n, w["stop"] + ext)))
    numbers = F.array_sort(F.array_distinct(F.flatten(reach)))
    side = lambda k: F.get(F.filter("_w", lambda w: (k >= w["start"] - ext) & (k <= w["stop"] + ext)), F.lit(0))
    part = lambda k: F.when(inside(k), "core").when(k < side(k)["start"], "before").otherwise("after")
    parts = F.transform(numbers, lambda k: F.struct(part(k).alias("part"), k.alias("sentence_no"), F.get("sents", k - 1).alias("text")))
    return both.withColumn("parts", parts).withColumn("n_sents", n).drop("_w", "sents")


def condense_grid(retrieved: DataFrame, docs: DataFrame, queries: DataFrame, idf: DataFrame, cells, ext: int = EXT, dim: int = DIM) -> dict[tuple[int, int], DataFrame]:
    """(qid, doc_id, rank, context) of each (window, overlap) cell. Windows of all cells are scored in one pass over the texts."""
    retrieved = checkpointed(retrieved.select("qid", "doc_id", "rank"))
    sents = checkpointed(docs.select("doc_id", V.sentences("text").alias("sents"), F.coalesce("text", F.lit("")).alias("whole")))
    best = checkpointed(best_windows(docs, retrieved, queries, idf, cells, 1, dim))
    out = {}
    for window, overlap in cells:
        made = extended(retrieved, best.where((F.col("window") == window) & (F.col("overlap") == overlap)), sents, ext)
        text = F.when(F.col("parts").isNull(), F.col("whole")).otherwise(merge(F.col("parts")))
        ranked = reorder(made.withColumn("context", text).withColumn("score", F.coalesce("score", F.lit(0.0))))
        out[window, overlap] = ranked.select("qid", "doc_id", F.col("new_rank").alias("rank"), "context")
    return out
