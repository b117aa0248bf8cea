"""SpotSigs: signatures of content-word chains that follow common-word anchors.

At every common word a spot signature is the anchor with the next CHAIN content words, STRIDE content words apart.
A text's fingerprint is the sorted set of its signatures' 32-bit hashes in hex, and the likeness of two fingerprints
is the Jaccard index of the sets. Matching deals sets to partitions by length, so that a pair within the threshold
lies in one partition or in neighbouring ones, and compares only sets that share one of their rarest signatures.

Defined results: a text without a complete anchored chain takes every content word as an anchor, a text without even
that its words, a text without words its characters; null is the empty text, whose fingerprint is empty; two empty
fingerprints have likeness 1. Equal texts have equal fingerprints. Whole texts are read, whatever their length.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from vecrag.llm import simhash
from vecrag.llm.common import checkpointed

CHAIN, STRIDE = 2, 1
#: Common words that anchor signatures (fixed values).
ANCHORS = frozenset(
    "the of and to in is was that a an it for on with as at by be are this from or "
    "la le les de des du et un une est que pour dans en au qui sur par pas il "
    "der die das und den von zu mit sich dem ein eine ist nicht auf im als auch "
    "el los las del y se por con para una su al lo no es".split()
)
WORD = re.compile(r"[^\W_]+")


def signature_set(text: str | None, chain: int = CHAIN, stride: int = STRIDE, anchors: frozenset[str] = ANCHORS) -> np.ndarray:
    """Sorted distinct 32-bit hashes of the text's spot signatures."""
    import xxhash

    if not text:
        return np.zeros(0, np.uint32)
    words = WORD.findall(text.lower())
    content = [w for w in words if w not in anchors]
    span = (chain - 1) * stride + 1
    found, j, last = set(), 0, len(content) - span
    for w in words:
        if w in anchors:
            if j <= last:
                found.add(w + ":" + " ".join(content[j : j + span : stride]))
        else:
            j += 1
    if not found:
        found = {" ".join(content[k : k + span : stride]) for k in range(last + 1)} or set(words) or {text}
    digest = xxhash.xxh32_intdigest
    return np.unique(np.fromiter((digest(s) for s in found), np.uint32, len(found)))


def as_text(signatures: np.ndarray) -> str:
    return signatures.astype(">u4").tobytes().hex()


def jaccard(a: np.ndarray, b: np.ndarray, least: float = 0.0) -> float:
    """Jaccard index of two sorted sets; 0 without a look inside where their sizes alone rule out `least`."""
    if not len(a) and not len(b):
        return 1.0
    if min(len(a), len(b)) < least * max(len(a), len(b)) or not len(a) or not len(b):
        return 0.0
    at = np.minimum(np.searchsorted(b, a), len(b) - 1)
    same = int((b[at] == a).sum())
    return same / (len(a) + len(b) - same)


def with_next(df: DataFrame, doc_id: str, text: str) -> tuple[DataFrame, int]:
    """Rows dealt to ranges of ascending id; each range also gets the rows that follow its last one (`late`).

    Range limits are ids of the table, one a partition, so what the driver sees is bounded by their number. The
    ids that open a range are dealt to the range before as well (the very first to the last range), which makes
    every row meet its successor in one shuffle.
    """
    session = df.sparkSession
    lowest = F.lit(-(1 << 63))
    keyed = df.select(F.col(doc_id).cast("long").alias("id"), F.coalesce(F.col(doc_id).cast("long"), lowest).alias("at"), F.col(text).cast("string").alias("text"))
    parts = int(session.conf.get("spark.sql.shuffle.partitions"))
    first = keyed.agg(F.min("at")).first()[0]
    limits = [] if first is None else sorted({first, *(int(x) for x in keyed.select(F.col("at").cast("long")).approxQuantile("at", [k / parts for k in range(1, parts)], 0.25 / parts))})
    limits = _exact(keyed, limits)
    edges = np.array(limits, np.int64)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = batch.column("at").to_numpy()
            part = np.searchsorted(edges, at, "right") - 1
            opens = np.flatnonzero(edges[part] == at)
            again = pa.RecordBatch.from_arrays([*batch.take(pa.array(opens)).columns, pa.array((part[opens] - 1) % len(edges), pa.int32()), pa.array(np.ones(len(opens), bool))], ["id", "at", "text", "part", "late"])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(part, pa.int32()), pa.array(np.zeros(len(at), bool))], ["id", "at", "text", "part", "late"])
            yield again

    out = keyed.mapInArrow(deal, "id long, at long, text string, part int, late boolean")
    return out.repartitionById(max(1, len(limits)), F.col("part")).sortWithinPartitions("late", "at", "text"), len(limits)


def _exact(keyed: DataFrame, limits: list[int]) -> list[int]:
    """The limits that are ids of the table (an approximate quantile of longs passes through a double)."""
    if all(abs(x) <= 1 << 53 for x in limits):
        return limits
    first = limits[0]
    near = [keyed.where(F.col("at") >= x).agg(F.min("at")).first()[0] for x in limits[1:]]
    return sorted({first, *(x for x in near if x is not None)})


def fingerprint_edits(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Fingerprint of every text, of its edited text (last quarter replaced by the next document's start) and likenesses."""
    dealt, _ = with_next(df, doc_id, text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            out: list[tuple] = []
            for k in range(batch.num_rows):
                body = batch.column("text")[k].as_py() or ""
                late = batch.column("late")[k].as_py()
                now = (batch.column("id")[k].as_py(), body, signature_set(body))
                if held is not None:
                    out.append(_edit(*held, body, now[2]))
                held = None if late else now
                if late:
                    break
                if len(out) >= 2000:
                    yield _rows(out)
                    out = []
            if out:
                yield _rows(out)
            if held is None and batch.num_rows and late:
                break
        for _ in batches:
            pass

    return dealt.select("id", "text", "late").mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


def _edit(doc_id: int | None, body: str, own: np.ndarray, following: str, of_next: np.ndarray) -> tuple:
    gone = len(body) // 4
    edited = body[: len(body) - gone] + following[:gone]
    changed = own if edited == body else signature_set(edited)
    sha = hashlib.sha256(edited.encode()).hexdigest()
    return doc_id, len(body), sha, as_text(own), as_text(changed), jaccard(own, changed), jaccard(own, of_next)


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names)


def near_duplicates(df: DataFrame, doc_id: str = "doc_id", text: str = "text", least: float = 0.8) -> DataFrame:
    """doc_id and class_id (smallest id reachable through pairs of sets with a Jaccard index of `least` or more).

    Equal sets are one node from the start. A set of n signatures can only match sets of least * n to n / least
    signatures, so lengths are cut into partitions whose limits grow by 1 / least, and a set meets its own partition
    and the next. Within those it meets the sets that share one of its n - ceil(least * n) + 1 rarest signatures; both
    prunings lose no pair. Sets that meet are compared nearest first and only as long as that can join two classes
    (simhash.grouped), so a signature of many copies makes no pair of all of them.
    """

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [signature_set(t).astype(np.int64) for t in batch.column("text").to_pylist()]
            fp = [simhash.wide_fingerprint(simhash.mixed(s)).tobytes() for s in found]
            same = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in found]
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(found, pa.list_(pa.int64())), pa.array(fp, pa.binary()), pa.array(same, pa.binary())], ["id", "sigs", "fp", "same"])

    given = df.select(F.col(doc_id).cast("long").alias("id"), F.col(text).cast("string").alias("text"))
    docs = checkpointed(given.mapInArrow(sets, "id long, sigs array<long>, fp binary, same binary"))
    nodes = docs.groupBy("same").agg(F.min("id").alias("node"), F.first("sigs").alias("sigs"), F.first("fp").alias("fp")).where("node is not null")
    growth = F.lit(float(np.log(1 / least)))
    nodes = checkpointed(nodes.withColumn("n", F.size("sigs")).withColumn("band", F.floor(F.log(F.greatest("n", F.lit(1))) / growth).cast("int")))
    spots = nodes.select("node", "n", "band", F.explode("sigs").alias("sig"))
    common = spots.groupBy("sig").agg(F.count("*").alias("df")).where("df > 1")  # a signature of one set lets it meet no other
    order = W.partitionBy("node").orderBy(F.coalesce("df", F.lit(1)), "sig")
    prefix = spots.join(common, "sig", "left").withColumn("r", F.row_number().over(order)).where((F.col("r") <= F.col("n") - F.ceil(F.lit(least) * F.col("n") - 1e-9) + 1) & F.col("df").isNotNull())
    dealt = checkpointed(prefix.select("node", F.explode(F.array(F.xxhash64("sig", "band"), F.xxhash64("sig", F.col("band") + 1))).alias("key")))
    shared = dealt.groupBy("key").agg(F.count("*").alias("members")).where("members > 1").select("key", F.ceil(F.col("members") / simhash.PART).cast("int").alias("parts"))
    met = dealt.join(shared, "key").join(nodes.select("node", "n", "fp"), "node").withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int"))
    found = simhash.grouped(checkpointed(met), nodes.select("node", F.col("sigs").alias("shingles")), least, few=1 << 40, dealt=False)
    classes = nodes.select("same", "node").withColumn("class", F.col("node"))
    if found is not None:
        classes = classes.drop("class").join(found.withColumnRenamed("component", "class"), "node", "left")
    return docs.select(F.col("id").alias("doc_id"), "same").join(classes, "same", "left").select("doc_id", F.coalesce("class", "node").alias("class_id"))
