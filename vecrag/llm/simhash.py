"""SimHash fingerprints linked within a Hamming radius by BK-trees of bounded shards.

Fingerprints that differ in at most `radius` of 64 bits agree on at least blocks - radius of `blocks` blocks, so each
distinct fingerprint is dealt to one shard for every choice of that many blocks and its bits there; two linked ones
meet in at least one shard. A shard is a BK-tree (children keyed by their integer distance to the parent) that is
searched by its own members along edges within the radius only. Shards over `SHARD` members are split: member group
pairs are dealt to shards of their own, so no task holds a hot shard and no link is lost. Within a shard links
contract to a spanning star; components are then found over all shards.

Defined results: text without words (or null) has fingerprint zero and links like any other; repeated ids share
their row's results; rows with a null id get the component of equal fingerprints, else null, and link nothing.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import partial
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import checkpointed, map_slices, numbered, release
from vecrag.llm.graph import components, contract

RADIUS, WORDS, BITS = 4, 4, 64
#: Members of a shard, and the mean size that the number of blocks is chosen for.
SHARD, MEAN = 20_000, 64
#: (query, node) pairs looked at in one vectorised step.
STEP = 1 << 18
#: More than any distance: keys of tree edges are node * STRIDE + distance.
STRIDE = 1 << 10
_LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))


def fingerprint(text: str | None, words: int = WORDS) -> int:
    """Majority bits of XXH64 (seed 42) over the word shingles, repeats included, as a signed 64-bit integer."""
    import xxhash

    tokens = (text or "").encode().translate(_LOWER).split()
    if not tokens:
        return 0
    joined = b" ".join(tokens)
    ends = np.cumsum([len(t) + 1 for t in tokens])
    starts = [0, *ends[:-1].tolist()]
    last = max(1, len(tokens) - words + 1)
    stops = (ends[min(words, len(tokens)) - 1 :] - 1).tolist()
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(joined[a:b], 42) for a, b in zip(starts[:last], stops, strict=False)), np.uint64, last)
    ones = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > last, bitorder="little").view("<i8")[0])


def fingerprints(df: DataFrame, doc_id: str = "doc_id", text: str = "text", words: int = WORDS) -> DataFrame:
    """(doc_id, fp) of every row."""

    def work(piece: pa.RecordBatch) -> pa.RecordBatch:
        fp = [fingerprint(t, words) for t in piece.column("text").to_pylist()]
        return pa.RecordBatch.from_arrays([piece.column("key"), pa.array(fp, pa.int64())], ["key", "fp"])

    given = df.select(F.col(doc_id).cast("long").alias("key"), F.col(text).cast("string").alias("text"))
    return map_slices(given, "text", work, "key long, fp long").withColumnRenamed("key", "doc_id")


def masks(n: int, radius: int = RADIUS) -> list[int]:
    """Bit masks of the block choices for n distinct fingerprints: more blocks, hence longer keys, for more of them."""
    for blocks in range(radius + 1, radius + 7):
        edges = [BITS * k // blocks for k in range(blocks + 1)]
        if n <= MEAN << (BITS * (blocks - radius) // blocks) or blocks == radius + 6:
            break
    block = [((1 << b) - 1) ^ ((1 << a) - 1) for a, b in zip(edges, edges[1:], strict=False)]
    signed = lambda x: x - (1 << BITS) if x >> (BITS - 1) else x
    return [signed(sum(c)) for c in combinations(block, blocks - radius)]


def differing(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Differing bits of fingerprints row by row: one 64-bit word each, or several as columns."""
    bits = np.bitwise_count(a ^ b)
    return bits.astype(np.int64) if bits.ndim == 1 else bits.sum(1, dtype=np.int64)


def bk_forest(fp: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """One BK-tree for each group: (root of each row, parent of each row, distance to it).

    All trees grow together, a level a round: of the rows that wait at an edge the first becomes its node, and the
    others wait at that node's edge for their distance to it.
    """
    n = len(fp)
    parent, edge, code = np.full(n, -1, np.int64), np.zeros(n, np.int64), group.astype(np.int64)
    waiting, root = np.arange(n), np.zeros(n, np.int64)
    first_round = True
    while len(waiting):
        rows = waiting[np.argsort(code[waiting], kind="stable")]
        head = np.append(True, code[rows[1:]] != code[rows[:-1]])
        node = rows[head][np.cumsum(head) - 1]
        if first_round:
            root[rows], first_round = node, False
        waiting, node = rows[~head], node[~head]
        parent[waiting] = node
        edge[waiting] = differing(fp[waiting], fp[node])
        code[waiting] = node * STRIDE + edge[waiting]
    return root, parent, edge


class Forest:
    """BK-trees of groups of fingerprints, searched by many queries at once along the edges within a radius."""

    def __init__(self, fp: np.ndarray, group: np.ndarray):
        self.fp = fp
        self.root, parent, edge = bk_forest(fp, group)
        children = np.flatnonzero(parent >= 0)
        keys = parent[children] * STRIDE + edge[children]
        order = np.argsort(keys, kind="stable")
        self.keys, self.children = keys[order], children[order]

    def visits(self, fp: np.ndarray, root: np.ndarray, radius: int | np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(query, node, distance) of all nodes that searches from the roots come to, in blocks of at most about STEP."""
        radius = np.broadcast_to(radius, len(fp))
        stack = [(np.arange(len(fp)), root)]
        while stack:
            query, node = stack.pop()
            if len(query) > STEP:
                half = len(query) // 2
                stack += [(query[:half], node[:half]), (query[half:], node[half:])]
                continue
            d = differing(fp[query], self.fp[node])
            yield query, node, d
            r = radius[query]
            lo = np.searchsorted(self.keys, node * STRIDE + np.maximum(0, d - r))
            hi = np.searchsorted(self.keys, node * STRIDE + np.minimum(STRIDE - 1, d + r), "right")
            width = hi - lo
            some = width > 0
            query, lo, width = query[some], lo[some], width[some]
            step = max(1, STEP // max(1, int(width.max(initial=1))))
            for part in range(0, len(query), step):
                w, at = width[part : part + step], lo[part : part + step]
                inside = np.arange(w.sum()) - np.repeat(np.cumsum(w) - w, w)
                stack.append((np.repeat(query[part : part + step], w), self.children[np.repeat(at, w) + inside]))


def linked(fp: np.ndarray, group: np.ndarray, radius: int = RADIUS) -> np.ndarray:
    """For each row the smallest row of its group that is reachable by links within the radius."""
    forest = Forest(fp, group)
    label = np.arange(len(fp))
    for query, node, d in forest.visits(fp, forest.root, radius):
        near = d <= radius
        contract(label, query[near], node[near])
    return label


def _shard_links(radius: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def solve(rows: np.ndarray) -> pa.RecordBatch:
            change = np.append(True, (rows[1:, :4] != rows[:-1, :4]).any(1))
            fp = np.ascontiguousarray(rows[:, 5:]).view(np.uint64)
            label = linked(fp[:, 0] if fp.shape[1] == 1 else fp, np.cumsum(change), radius)
            moved = np.flatnonzero(label != np.arange(len(label)))
            return pa.RecordBatch.from_arrays([pa.array(rows[moved, 4]), pa.array(rows[label[moved], 4])], ["a", "b"])

        for batch in batches:
            rows = np.column_stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]).astype(np.int64)
            if not len(rows):
                continue
            rows = np.vstack([*held, rows])
            last = np.flatnonzero((rows[:, :4] != rows[-1, :4]).any(1))
            cut = last[-1] + 1 if len(last) else 0  # the last shard may go on in the next batch
            if cut:
                yield solve(rows[:cut])
            held = [rows[cut:]]
        if held and len(held[0]):
            yield solve(held[0])

    return run


def near_links(reps: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Links (a, b) that connect all `reps` (fp, rep) whose distinct fingerprints are within the radius, by shard."""
    choices = masks(reps.count(), radius)
    keyed = reps.select("fp", "rep", F.explode(F.array(*(F.struct(F.lit(k).alias("choice"), F.col("fp").bitwiseAND(F.lit(m)).alias("bits")) for k, m in enumerate(choices)))).alias("s")).select("s.choice", "s.bits", "fp", "rep")
    return _by_shard(keyed, ["fp"], radius)


def _by_shard(keyed: DataFrame, words: list[str], radius: int) -> DataFrame:
    """Links within the radius of all rows (choice, bits, rep, words..) that share choice and bits."""
    hot = keyed.groupBy("choice", "bits").agg(F.count("*").alias("members")).where(F.col("members") > SHARD)
    hot = checkpointed(hot.select("choice", "bits", F.ceil(F.col("members") / SHARD).cast("int").alias("parts")))
    keys = ["choice", "bits", "low", "high"]
    if hot.isEmpty():
        dealt = keyed.select("choice", "bits", F.lit(0).alias("low"), F.lit(0).alias("high"), "rep", *words)
    else:
        dealt = keyed.join(hot, ["choice", "bits"], "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
        own = F.pmod(F.xxhash64(*words), F.col("parts")).cast("int")
        dealt = dealt.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        dealt = dealt.select("choice", "bits", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "rep", *words)
    return dealt.repartition(*keys).sortWithinPartitions(*keys, *words).mapInArrow(_shard_links(radius), "a long, b long")


def cluster(df: DataFrame, doc_id: str = "doc_id", text: str = "text", radius: int = RADIUS, words: int = WORDS) -> DataFrame:
    """doc_id, fingerprint (16 hex digits) and component_id (smallest doc_id reachable) of every row."""
    prints = checkpointed(fingerprints(df, doc_id, text, words))
    reps = checkpointed(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")))
    found = components(near_links(reps.where("rep is not null"), radius))
    home = reps.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    out = prints.join(home, "fp")
    return out.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


# -- similarity of five-word shingle sets ------------------------------------------------------------------------------
#: 64-bit words of a wide fingerprint, the shingle length of the pipeline's stage and its similarity.
WIDE, SHINGLE, SIMILARITY = 4, 5, 0.8
#: Minima in a shard key, and the share of pairs exactly at the similarity that may meet in no shard.
ROWS, MISS = 6, 1e-3
#: Standard deviations of the distance at the similarity that the radius allows for, and the number of shingles under which
#: no radius holds (the bits of few shingles differ by chance).
SPREAD, FEW = 3.0, 64
#: Candidates that a member of a shard has checked, nearest first, round by round; a last round checks all that are left.
NEAREST = (1, 4)
#: Members of a part of a large shard, and those of each part nearest to its majority fingerprint, which all parts meet.
PART, HEADS = 4096, 4
#: Shingles that members of a shard bring to a part of it in the last round, and what a member counts for at least.
MOST, LEAST = 1 << 21, 512
#: Rows of a table that may be broadcast (under 20 bytes each).
SMALL = 1_000_000
_ODD = np.random.default_rng(42).integers(0, 1 << 63, 4096, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_MIX = np.uint64(0xFF51AFD7ED558CCD)


def shingle_set(text: str | None, words: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles (of all words, if there are fewer)."""
    import xxhash

    tokens = (text or "").encode().translate(_LOWER).split()
    if not tokens:
        return np.zeros(0, np.uint64)
    joined = b" ".join(tokens)
    ends = np.cumsum([len(t) + 1 for t in tokens])
    starts = [0, *ends[:-1].tolist()]
    last = max(1, len(tokens) - words + 1)
    stops = (ends[min(words, len(tokens)) - 1 :] - 1).tolist()
    digest = xxhash.xxh3_64_intdigest
    return np.unique(np.fromiter((digest(joined[a:b]) for a, b in zip(starts[:last], stops, strict=False)), np.uint64, last))


def wide_fingerprint(shingles: np.ndarray) -> np.ndarray:
    """WIDE * 64 majority bits over a shingle set: a SimHash of WIDE words, each of its own mix of the hashes."""
    if not len(shingles):
        return np.zeros(WIDE, np.uint64)
    ones = np.zeros(WIDE * 64, np.int64)
    for at in range(0, len(shingles), 255):
        h = shingles[at : at + 255, None] * _ODD[:WIDE]
        h = (h ^ (h >> np.uint64(32))) * _MIX
        h ^= h >> np.uint64(29)
        ones += np.unpackbits(h.view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.uint8)
    return np.packbits(2 * ones > len(shingles), bitorder="little").view("<u8")


def mixed(values: np.ndarray) -> np.ndarray:
    """64-bit hashes of small integers."""
    h = values.astype(np.uint64) * _MIX
    return (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)


def differing_share(similarity: float) -> float:
    """Expected share of differing bits at a Jaccard index: the angle between the sets' indicator vectors over pi."""
    return float(np.arccos(min(1.0, 2 * similarity / (1 + similarity))) / np.pi)


def wide_radius(similarity: float = SIMILARITY) -> int:
    """Differing bits up to which a pair is a candidate: SPREAD deviations over the mean at the similarity."""
    p, bits = differing_share(similarity), 64 * WIDE
    return int(np.ceil(bits * p + SPREAD * np.sqrt(bits * p * (1 - p))))


def bands(similarity: float = SIMILARITY) -> int:
    """Shard keys of ROWS minima, so that at most MISS of the pairs at the similarity share none, whatever the table's size."""
    return int(np.ceil(np.log(MISS) / np.log1p(-(similarity**ROWS)))) if similarity < 1 else 1


def band_keys(shingles: np.ndarray, n: int) -> np.ndarray:
    """One key for each of n bands: a hash of the minima of ROWS random orders of the set."""
    odd = _ODD[-n * ROWS :]
    least = np.full(n * ROWS, np.iinfo(np.uint64).max)
    for at in range(0, len(shingles), 256):
        np.minimum(least, (shingles[at : at + 256, None] * odd).min(0), out=least)
    key = np.arange(n, dtype=np.uint64)
    for column in least.reshape(n, ROWS).T:
        key = (key ^ column) * _MIX
        key ^= key >> np.uint64(33)
    return key.view(np.int64)


def _by_part(solve: Callable[[dict[str, np.ndarray]], pa.RecordBatch | None]):
    """Apply solve to whole (key, part) groups of rows that come sorted; one may go on in the next batch."""

    def arrays(table: pa.Table) -> dict[str, np.ndarray]:
        out = {c: table[c].to_numpy() for c in table.schema.names if c != "fp"}
        if "shingles" in out:
            out["shingles"] = np.fromiter((v.view(np.uint64) for v in out["shingles"]), object, len(out["shingles"]))  # sorted as such
        out["fp"] = np.frombuffer(b"".join(table["fp"].to_pylist()), "<u8").reshape(-1, WIDE)
        out["group"] = np.cumsum(np.append(0, (np.diff(out["key"]) != 0) | (np.diff(out["part"]) != 0)))
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            if not batch.num_rows:
                continue
            key, part = (batch.column(c).to_numpy() for c in ("key", "part"))
            before = np.flatnonzero((key != key[-1]) | (part != part[-1]))
            cut = int(before[-1]) + 1 if len(before) else 0
            if cut:
                got = solve(arrays(pa.Table.from_batches([*held, batch.slice(0, cut)])))
                held = []
                if got is not None:
                    yield got
            held.append(batch.slice(cut))
        if held:
            got = solve(arrays(pa.Table.from_batches(held)))
            if got is not None:
                yield got
        release()

    return run


def _main(group: np.ndarray, comp: np.ndarray) -> np.ndarray:
    """For each row whether it is of its group's largest component, if that has several rows (the smallest on ties)."""
    order = np.lexsort((comp, group))
    head = np.append(True, (np.diff(group[order]) != 0) | (np.diff(comp[order]) != 0))
    run = np.cumsum(head) - 1
    size, of = np.bincount(run), group[order][head]
    best = np.lexsort((comp[order][head], -size, of))
    first = best[np.append(True, np.diff(of[best]) != 0)]
    chosen = np.zeros(len(size), bool)
    chosen[first] = size[first] > 1
    out = np.empty(len(group), bool)
    out[order] = chosen[run]
    return out


def _within(x: dict[str, np.ndarray], asks: np.ndarray, there: np.ndarray, similarity: float, few: int) -> Iterator[np.ndarray]:
    """(asking row, row that is there, differing bits) of the pairs of different components within the radius, by blocks of asking rows."""
    group, comp, n = x["group"], x["comp"], x["n"]
    low, high = np.full(int(group[-1]) + 1, np.iinfo(np.int64).max), np.full(int(group[-1]) + 1, np.iinfo(np.int64).min)
    np.minimum.at(low, group, comp)
    np.maximum.at(high, group, comp)
    mixed = low < high  # groups of more than one component
    query, target = np.flatnonzero(asks & mixed[group]), np.flatnonzero(there & mixed[group])
    if not len(query) or not len(target):
        return
    forest = Forest(x["fp"][target], group[target])
    first = np.full(len(mixed), -1)
    first[group[target]] = forest.root
    query = query[first[group[query]] >= 0]
    size = np.bincount(group[target], minlength=len(mixed))[group[query]]
    radius = np.where(n[query] * similarity < few, WIDE * 64, wide_radius(similarity))
    at = 0
    ends = np.cumsum(size)
    while at < len(query):  # queries whose groups have about STEP targets together
        stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + STEP, "right")))
        block = query[at:stop]
        hits = []
        for q, node, d in forest.visits(x["fp"][block], first[group[block]], radius[at:stop]):
            a, b = block[q], target[node]
            small = np.minimum(n[a], n[b])
            near = ((d <= wide_radius(similarity)) | (small < few)) & (comp[a] != comp[b]) & (small >= (similarity - 1e-9) * np.maximum(n[a], n[b]))
            hits.append(np.column_stack([a[near], b[near], d[near]]))
        yield np.concatenate(hits)
        at = stop


def _candidates(k: int, similarity: float, few: int, x: dict[str, np.ndarray]) -> pa.RecordBatch | None:
    """Pairs of different components within the radius: of each asking member the k nearest.

    Members outside their group's largest component ask. In a part of a large shard the heads of other parts are there as guests.
    """
    guest, node = x["guest"], x["node"]
    found: list[np.ndarray] = []
    for h in _within(x, ~guest & ~_main(x["group"], x["comp"]), np.ones(len(guest), bool), similarity, few):
        h = h[np.lexsort((node[h[:, 1]], h[:, 2], h[:, 0]))]
        rank = np.arange(len(h)) - np.searchsorted(h[:, 0], h[:, 0])
        found.append(node[h[rank < k, :2]])
    if not found:
        return None
    pairs = np.unique(np.sort(np.concatenate(found), axis=1), axis=0)
    return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], ["a", "b"]) if len(pairs) else None


class _Overlaps:
    """How many values the sets of a group have in common, by the rows that hold each value."""

    def __init__(self, sets: np.ndarray):
        self.ends = np.append(0, np.cumsum([len(s) for s in sets]))
        _, self.of, self.count = np.unique(np.concatenate(list(sets)), return_inverse=True, return_counts=True)
        row = np.repeat(np.arange(len(sets)), np.diff(self.ends))
        self.rows, self.first = row[np.argsort(self.of, kind="stable")], np.cumsum(self.count) - self.count
        self.shared = np.bincount(row[self.count[self.of] > 1], minlength=len(sets))  # values of a row that others have too

    def __call__(self, row: int) -> np.ndarray:
        """Of one row with each row; a value that it has alone counts for none."""
        values = self.of[self.ends[row] : self.ends[row + 1]]
        values = values[self.count[values] > 1]
        width = self.count[values]
        at = np.repeat(self.first[values] - (np.cumsum(width) - width), width) + np.arange(width.sum())
        return np.bincount(self.rows[at], minlength=len(self.shared))


def _joining(similarity: float, few: int, x: dict[str, np.ndarray]) -> pa.RecordBatch | None:
    """Links (a, b) that join the components whose asking members lie within the radius and have the similarity.

    An asking member counts what it shares with the others of its group only if the values that it and any of these share with
    anyone could be enough.
    """
    n, node, group = x["n"].astype(np.int64), x["node"], x["group"]
    top, of = np.unique(x["comp"], return_inverse=True)
    top = list(range(len(top)))

    def head(c: int) -> int:
        while top[c] != c:
            top[c] = c = top[top[c]]
        return c

    alike = lambda same, both: same >= (similarity - 1e-9) * (both - same)
    now, links = -1, []
    for h in _within(x, x["asks"], x["there"], similarity, few):
        h = h[np.argsort(h[:, 0], kind="stable"), :2]
        for some in np.split(h, np.flatnonzero(np.diff(h[:, 0])) + 1):
            if not len(some):
                continue
            a, b = int(some[0, 0]), some[:, 1]
            if group[a] != now:
                now, start = group[a], int(np.searchsorted(group, group[a]))
                overlaps = _Overlaps(x["shingles"][start : int(np.searchsorted(group, now, "right"))])
            b = b[alike(np.minimum(overlaps.shared[a - start], overlaps.shared[b - start]), n[a] + n[b])]
            if not len(b):
                continue
            for c in b[alike(overlaps(a - start)[b - start], n[a] + n[b])].tolist():
                low, high = sorted((head(of[a]), head(of[c])))
                if low != high:
                    top[high] = low
                    links.append((node[a], node[c]))
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*links, strict=True)], ["a", "b"]) if links else None


def _apart(similarity: float, few: int, x: dict[str, np.ndarray]) -> pa.RecordBatch | None:
    """All pairs of different components within the radius of asking members."""
    found = [np.unique(np.sort(x["node"][h[:, :2]], axis=1), axis=0) for h in _within(x, x["asks"], x["there"], similarity, few)]
    return pa.RecordBatch.from_arrays([pa.array(c) for c in np.unique(np.concatenate(found), axis=0).T], ["a", "b"]) if found else None


def _heads(x: dict[str, np.ndarray]) -> pa.RecordBatch | None:
    """The members of each part that lie nearest to the majority of its fingerprints: the middle of a star of copies is one."""
    out = []
    starts = np.flatnonzero(np.append(True, np.diff(x["group"]) != 0))
    for a, b in zip(starts, np.append(starts[1:], len(x["group"])), strict=True):
        ones = np.zeros(WIDE * 64, np.int64)
        for at in range(a, b, 1024):
            ones += np.unpackbits(np.ascontiguousarray(x["fp"][at : min(b, at + 1024)]).view(np.uint8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        middle = np.packbits(2 * ones > b - a, bitorder="little").view("<u8")
        out.append(a + np.lexsort((x["node"][a:b], differing(x["fp"][a:b], middle)))[:HEADS])
    rows = np.concatenate(out)
    return pa.RecordBatch.from_arrays([pa.array(x["key"][rows]), pa.array(x["node"][rows])], ["key", "node"])


def _dealt(rows: DataFrame, solve, schema: str) -> DataFrame:
    return rows.repartition("key", "part").sortWithinPartitions("key", "part", "node").mapInArrow(_by_part(solve), schema)


def _labelled(met: DataFrame, found: DataFrame | None) -> DataFrame:
    """The members with their component so far: themselves, where no link has met them."""
    if found is None:
        return met.withColumn("comp", F.col("node"))
    labels = found.withColumnRenamed("component", "label")
    return met.join(F.broadcast(labels) if found.count() <= SMALL else labels, "node", "left").withColumn("comp", F.coalesce("label", "node")).drop("label")


def _round(met: DataFrame, found: DataFrame | None, heads: DataFrame | None, k: int, similarity: float, few: int) -> DataFrame:
    """Candidate pairs (a, b) of one round over the members (key, parts, part, node, n, fp) of all shards."""
    rows = _labelled(met, found)
    cols = ["key", "part", "node", "n", "comp", "fp"]
    all_rows = rows.select(*cols, F.lit(False).alias("guest"))
    if heads is not None:
        guests = rows.where("parts > 1").join(F.broadcast(heads) if heads.count() <= SMALL else heads, ["key", "node"], "left_semi")
        guests = guests.withColumn("part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
        all_rows = all_rows.unionByName(guests.select(*cols, F.lit(True).alias("guest")))
    return _dealt(all_rows, partial(_candidates, k, similarity, few), "a long, b long").distinct()


def _rest(met: DataFrame, found: DataFrame | None, sets: DataFrame | None, similarity: float, few: int) -> DataFrame:
    """Links (a, b) of the last round: in shards of several components all pairs of these are looked at where their sets meet;
    without `sets` the pairs, to be checked.

    Members outside a shard's largest component ask all its members. Where these have over MOST shingles, parts of the members
    meet blocks of those that ask, each pair of a part and a block in a place of its own. Only links leave a task, fewer
    than its components; pairs do not.
    """
    rows = _labelled(met, found).withColumn("w", F.greatest("n", F.lit(LEAST)).cast("long"))
    sizes = rows.groupBy("key", "comp").agg(F.sum("w").alias("w")).groupBy("key").agg(F.count("*").alias("comps"), F.sum("w").alias("all"), F.max(F.struct("w", "comp")).alias("main")).where("comps > 1")
    share = lambda w: F.ceil(w / MOST).cast("int")
    sizes = sizes.select("key", F.col("main.comp").alias("main"), share(F.col("all")).alias("most"), share(F.col("all") - F.col("main.w")).alias("blocks"))
    rows = rows.join(sizes, "key").withColumn("asks", F.col("comp") != F.col("main"))
    own = lambda n: F.pmod(F.xxhash64("node"), F.col(n)).cast("int")
    place = lambda part, asks, there: F.struct(part.alias("at"), asks.alias("ask"), F.lit(there).alias("there"))
    members = F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), lambda b: place(own("most") * F.col("blocks") + b, F.lit(False), True))
    asking = F.transform(F.sequence(F.lit(0), F.col("most") - 1), lambda p: place(p * F.col("blocks") + own("blocks"), F.lit(True), False))
    places = F.when(F.col("most") * F.col("blocks") == 1, F.array(place(F.lit(0), F.col("asks"), True))).when(F.col("asks"), F.concat(members, asking)).otherwise(members)
    dealt = rows.select("key", "node", "n", "comp", "fp", F.explode(places).alias("p")).select("key", F.col("p.at").alias("part"), "node", "n", "comp", "fp", F.col("p.ask").alias("asks"), F.col("p.there").alias("there"))
    if sets is None:
        return _dealt(dealt, partial(_apart, similarity, few), "a long, b long").distinct()
    return _dealt(dealt.join(sets, "node"), partial(_joining, similarity, few), "a long, b long")


def _stars(found: DataFrame) -> DataFrame:
    """The links (a, b) of each node with its component's smallest, which stand for all links so far."""
    return found.select(F.col("node").alias("a"), F.col("component").alias("b"))


def _checked(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """(a, b, ok): whether the Jaccard index of a pair's shingle sets is the similarity or more."""
    both = F.size(F.array_intersect("sa", "sb"))
    left, right = (sets.select(F.col("node").alias(x), F.col("shingles").alias(f"s{x}")) for x in "ab")
    ok = both >= F.lit(similarity - 1e-9) * (F.size("sa") + F.size("sb") - both)
    return pairs.join(left, "a").join(right, "b").select("a", "b", ok.alias("ok"))


def grouped(met: DataFrame, sets: DataFrame, similarity: float, few: int = FEW, dealt: bool = True) -> DataFrame | None:
    """Components of all pairs that meet in a shard, lie within the radius and have the similarity; None if there are none.

    met: the members (key, parts, part, node, n, fp) of the shards; sets: (node, shingles). Pairs with a set of fewer than
    `few` members need not lie within the radius.

    A member's nearest candidates are checked first. That joins most of a large group, after which only pairs of
    different components are left; the last round looks at all of those. With `dealt` the sets go to the shards for it, once a
    shard; without, for members of very many shards, the pairs are sent to the sets.
    """
    heads = None
    large = met.where("parts > 1")
    if not large.isEmpty():
        heads = checkpointed(_dealt(large, _heads, "key long, node long"))
    found = failed = None
    for k in NEAREST:
        pairs = _round(met, found, heads, k, similarity, few)
        if failed is not None:
            pairs = pairs.join(failed, ["a", "b"], "left_anti")
        got = checkpointed(_checked(pairs, sets, similarity))
        new, bad = got.where("ok").select("a", "b"), got.where("not ok").select("a", "b")
        failed = bad if failed is None else failed.unionByName(bad)
        if not new.isEmpty():
            found = components(new if found is None else _stars(found).unionByName(new))
    rest = _rest(met, found, sets if dealt else None, similarity, few)
    if not dealt:
        rest = _checked(rest.join(failed, ["a", "b"], "left_anti"), sets, similarity).where("ok").select("a", "b")
    new = checkpointed(rest)
    if new.isEmpty():
        return found
    return components(new if found is None else _stars(found).unionByName(new))


def similar(df: DataFrame, doc_id: str = "doc_id", text: str = "text", similarity: float = SIMILARITY, words: int = SHINGLE) -> DataFrame:
    """doc_id, body (digest of the shingle set) and component_id: texts linked where the Jaccard index of their word
    shingle sets is `similarity` or more.

    Fingerprints of WIDE * 64 bits are dealt to shards by minima of the shingle set (`bands`: their number does not grow
    with the table), each shard's BK-tree is searched within a radius that allows for the similarity, and every candidate
    that could still join two components is checked against the sets themselves. Equal sets are one node.
    """
    n = bands(similarity)

    def read(texts: list[str | None]) -> tuple[list[np.ndarray], pa.Array]:
        import xxhash

        sets = [shingle_set(t, words) for t in texts]
        return sets, pa.array([xxhash.xxh3_128_digest(s.tobytes()) for s in sets], pa.binary())

    def sketch(piece: pa.RecordBatch) -> pa.RecordBatch:
        sets, body = read(piece.column("text").to_pylist())
        keys = pa.array([band_keys(s, n) if len(s) else [] for s in sets], pa.list_(pa.int64()))
        fp = pa.array([wide_fingerprint(s).tobytes() for s in sets], pa.binary())
        return pa.RecordBatch.from_arrays([piece.column("key"), body, pa.array([len(s) for s in sets], pa.int32()), fp, keys], ["doc_id", "body", "n", "fp", "keys"])

    def whole(piece: pa.RecordBatch) -> pa.RecordBatch:
        sets, body = read(piece.column("text").to_pylist())
        return pa.RecordBatch.from_arrays([piece.column("key"), body, pa.array([s.view(np.int64) for s in sets], pa.list_(pa.int64()))], ["node", "body", "shingles"])

    given = df.select(F.col(doc_id).cast("long").alias("key"), F.col(text).cast("string").alias("text"))
    prints = checkpointed(map_slices(given, "text", sketch, "doc_id long, body binary, n int, fp binary, keys array<long>"))
    reps = checkpointed(prints.groupBy("body").agg(F.min("doc_id").alias("node"), F.first("n").alias("n"), F.first("fp").alias("fp"), F.first("keys").alias("keys")))
    some = reps.where("node is not null")
    dealt = some.select("node", F.explode("keys").alias("key"))
    shared = dealt.groupBy("key").agg(F.count("*").alias("members")).where("members > 1").select("key", F.ceil(F.col("members") / PART).cast("int").alias("parts"))
    own = dealt.join(shared, "key").join(some.select("node", "n", "fp"), "node")
    met = checkpointed(own.withColumn("part", F.pmod(F.xxhash64("node"), F.col("parts")).cast("int")))
    members = checkpointed(met.select("node").distinct())
    wanted = F.broadcast(members) if members.count() <= SMALL else members
    sets = map_slices(given.join(wanted, F.col("key") == F.col("node"), "left_semi"), "text", whole, "node long, body binary, shingles array<long>")
    sets = checkpointed(sets.join(some.select("node", "body"), ["node", "body"], "left_semi").dropDuplicates(["node", "body"]))
    found = grouped(met, sets, similarity)
    if found is None:
        return prints.join(reps.select("body", F.col("node").alias("component_id")), "body").select("doc_id", "body", "component_id")
    home = reps.select("body", "node").join(found, "node", "left").select("body", F.coalesce("component", "node").alias("component_id"))
    return prints.join(home, "body").select("doc_id", "body", "component_id")


def keep_one(df: DataFrame, doc_id: str = "doc_id", text: str = "text", similarity: float = SIMILARITY, words: int = SHINGLE) -> DataFrame:
    """Of each group of similar texts the row with the smallest id stays, with all its columns; so do rows without id.

    Rows that repeat both id and text count once.
    """
    given, back = numbered(df)
    key, body = (f"c{df.columns.index(c)}" for c in (doc_id, text))
    groups = checkpointed(similar(given, key, body, similarity, words).where("doc_id is not null"))
    going = groups.where("doc_id <> component_id").select("doc_id").distinct()
    kept = given.join(going, F.col(key) == F.col("doc_id"), "left_anti")
    repeated = groups.groupBy("doc_id", "body").agg(F.count("*").alias("n")).where("n > 1")
    if repeated.isEmpty():
        return back(kept)
    return back(kept.withColumn("same", F.xxhash64(F.col(body))).dropDuplicates([key, "same"]))
