"""Byte-level BPE encoding and decoding by recursive DuckDB queries in each partition.

A pre-token ("word") that is no token itself is cut into pieces where no token of the vocabulary can lie across the cut
(judged by the two and three bytes around it), so that merges of one piece never touch another. Each distinct piece
becomes token-position rows, at first one row a byte. A recursive query joins neighbouring rows with the merge table,
contracts each piece's leftmost pair of lowest rank, and repeats until no piece has a merge left; ordered aggregation
then gives each piece's ids and its decoded bytes. Pieces over `SHORT` bytes go through a form of the query that contracts
many places of a piece at once (see `LONG_SQL`). Work in a query is bounded, and a worker remembers the words and pieces
it has met, over all its tasks, up to fixed numbers of them.

Defined results: null text encodes as the empty text (0 ids, digests of no bytes); repeated rows
give repeated results; texts are taken whole whatever their length; special tokens are never made.
"""

from __future__ import annotations

import base64
import hashlib
import re
import zlib
from collections.abc import Iterator
from itertools import chain, islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import KEPT, release, slices, small_batches

#: Bytes of a short piece, and pieces and bytes in one recursive query: they bound DuckDB's memory.
SHORT, PIECES, BYTES = 64, 10_000, 160_000
#: Rows that a query over long pieces may gather in its rounds.
LONG_ROWS = 1_000_000
#: Words and pieces that a worker remembers before it starts anew.
WORDS_KEPT, PIECES_KEPT = 100_000, 150_000
#: Words of a text that are encoded together.
TOGETHER = 500_000

#: State rows are (piece, pos, tok, nxt, round): `nxt` is the position of the piece's next token. A round contracts one
#: pair of each piece that still has one; `key` names a pair in the merge table.
MERGE_SQL = """
WITH RECURSIVE state(piece, pos, tok, nxt, round) AS (
    SELECT piece, pos, tok, nxt, 0 FROM start
  UNION ALL
    SELECT piece, pos, tok, nxt, round FROM (
        WITH pairs AS (
            SELECT a.piece, m.rank * 4294967296 + a.pos AS pick, b.pos AS gone, b.nxt AS after
            FROM state a JOIN state b ON b.piece = a.piece AND b.pos = a.nxt JOIN merges m ON m.key = a.tok * 65536 + b.tok
        ), best AS (
            SELECT piece, min(pick) AS pick, arg_min(gone, pick) AS gone, arg_min(after, pick) AS after FROM pairs GROUP BY piece
        )
        SELECT s.piece, s.pos, s.round + 1 AS round,
               CASE WHEN s.pos = best.pick % 4294967296 THEN best.pick // 4294967296 ELSE s.tok END AS tok,
               CASE WHEN s.pos = best.pick % 4294967296 THEN best.after ELSE s.nxt END AS nxt
        FROM state s JOIN best ON s.piece = best.piece
        WHERE s.pos <> best.gone
    )
), final AS (
    SELECT piece, max(round) AS round FROM state GROUP BY piece
)
SELECT piece, {aggregates}
FROM (SELECT s.piece, s.pos, s.tok, v.hex
      FROM state s JOIN final f ON s.piece = f.piece AND s.round = f.round JOIN vocab v ON v.tok = s.tok
      ORDER BY s.piece, s.pos)
GROUP BY piece
"""
#: Aggregates over rows that come in order are cheaper; that they did is checked by the positions, and the second form,
#: which orders by itself, is the way out.
IN_ORDER = "list(tok) AS ids, list(pos) AS places, string_agg(hex, '') AS decoded"
ORDERED = "list(tok ORDER BY pos) AS ids, list(pos ORDER BY pos) AS places, string_agg(hex, '' ORDER BY pos) AS decoded"

#: The same for long pieces: a round contracts the pair of lowest rank at its leftmost place and, right of it, at every
#: place that leaves at least one token between two contractions (places that touch form chains, of which every fourth
#: position is taken). One at a time they would be contracted in the same order, as long as none of them makes a pair of a
#: lower rank: `low` is the rank of the last round, and a piece whose ranks fall comes back as `fell` and is done again
#: by MERGE_SQL's rule.
LONG_SQL = """
WITH RECURSIVE state(piece, pos, tok, low, fell, round) AS (
    SELECT piece, pos, tok, low, false, 0 FROM start
  UNION ALL
    SELECT piece, pos, tok, low, fell, round FROM (
        WITH n AS (
            SELECT *, lead(tok) OVER (PARTITION BY piece ORDER BY pos) AS after FROM state WHERE round < $rounds AND NOT fell
        ), pairs AS (
            SELECT n.piece, n.pos, m.rank FROM n JOIN merges m ON m.key = n.tok * 65536 + n.after
        ), least AS (
            SELECT piece, min(rank) AS rank FROM pairs GROUP BY piece
        ), places AS (
            SELECT p.piece, p.pos, p.rank, p.pos - lag(p.pos) OVER (PARTITION BY p.piece ORDER BY p.pos) AS gap
            FROM pairs p JOIN least l ON l.piece = p.piece AND l.rank = p.rank
        ), chains AS (
            SELECT piece, pos, rank, pos - max(CASE WHEN gap <= 2 THEN NULL ELSE pos END) OVER (PARTITION BY piece ORDER BY pos ROWS UNBOUNDED PRECEDING) AS far FROM places
        ), taken AS (
            SELECT piece, pos, rank FROM chains WHERE far % 4 = 0
        )
        SELECT n.piece, row_number() OVER (PARTITION BY n.piece ORDER BY n.pos) - 1 AS pos, coalesce(t.rank, n.tok) AS tok,
               least.rank AS low, least.rank < n.low AS fell, n.round + 1 AS round
        FROM n JOIN least ON least.piece = n.piece
        LEFT JOIN taken t ON t.piece = n.piece AND t.pos = n.pos
        LEFT JOIN taken g ON g.piece = n.piece AND g.pos = n.pos - 1
        WHERE g.pos IS NULL
    )
), final AS (
    SELECT piece, max(round) AS round FROM state GROUP BY piece
)
SELECT s.piece, any_value(s.round) AS round, any_value(s.low) AS low, bool_or(s.fell) AS fell,
       list(s.tok ORDER BY s.pos) AS ids, string_agg(v.hex, '' ORDER BY s.pos) AS decoded
FROM state s JOIN final f ON s.piece = f.piece AND s.round = f.round JOIN vocab v ON v.tok = s.tok GROUP BY s.piece
"""

DECODE_SQL = """
SELECT r.row, string_agg(v.hex, '' ORDER BY r.pos) AS decoded
FROM pieces r JOIN vocab v ON v.tok = r.tok GROUP BY r.row
"""


def read_ranks(path: str) -> dict[bytes, int]:
    """The rank file of a public tokenizer: a base64 token and its rank on each line."""
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


def merge_table(ranks: dict[bytes, int]) -> pa.Table:
    """Every pair of tokens whose concatenation is a token: key = left * 65536 + right, rank of the whole."""
    if max(ranks.values(), default=0) >= 1 << 16:
        raise ValueError("ids must be below 65536")
    keys, merged = [], []
    for token, rank in ranks.items():
        for cut in range(1, len(token)):
            left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
            if left is not None and right is not None:
                keys.append(left << 16 | right)
                merged.append(rank)
    return pa.table({"key": pa.array(keys, pa.int64()), "rank": pa.array(merged, pa.int64())})


def latin_pattern(pattern: str) -> re.Pattern | None:
    """The pattern for `re` over texts of code points under 256, or None if it holds what the two engines may read apart.

    Classes are spelt out as `regex` has them; `re` is about twice as fast.
    """
    import regex

    spelt = {name: "".join(re.escape(chr(c)) for c in range(256) if regex.fullmatch(name, chr(c))) for name in (r"\p{L}", r"\p{N}", r"\s")}
    out, at, inside = [], 0, False
    while at < len(pattern):
        name = next((n for n in spelt if pattern.startswith(n, at)), None)
        if name:
            out.append(spelt[name] if inside else f"[{spelt[name]}]")
            at += len(name)
        elif pattern.startswith(r"\S", at) and not inside:
            out.append(f"[^{spelt[chr(92) + 's']}]")
            at += 2
        elif pattern[at] in "\\.^$#&~" and not (inside and pattern[at] == "^") or pattern.startswith("(?", at) and pattern[at : at + 3] not in ("(?!", "(?:"):
            return None
        else:
            inside = (inside or pattern[at] == "[") and pattern[at] != "]"
            out.append(pattern[at])
            at += 1
    return re.compile("".join(out))


class Ragged:
    """Rows of differing length in one buffer that grows."""

    def __init__(self, kind: type):
        self.flat, self.starts, self.rows = np.empty(1 << 16, kind), np.zeros(1 << 12, np.int64), 0

    def append(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        end, rows = int(self.starts[self.rows]), self.rows + len(sizes)
        if end + len(flat) > len(self.flat):
            self.flat = np.concatenate([self.flat[:end], np.empty(end + 2 * len(flat), self.flat.dtype)])
        if rows >= len(self.starts):
            self.starts = np.concatenate([self.starts, np.empty(rows + len(sizes), np.int64)])
        self.flat[end : end + len(flat)] = flat
        self.starts[self.rows + 1 : rows + 1] = end + np.cumsum(sizes)
        self.rows = rows

    def take(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows one after the other, and their sizes."""
        first = self.starts[rows]
        sizes = self.starts[rows + 1] - first
        return _ragged(self.flat, first, sizes), sizes


def _ragged(flat: np.ndarray, first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    return flat[np.repeat(first - (np.cumsum(sizes) - sizes), sizes) + np.arange(int(sizes.sum()))]


class Numbered(dict):
    """Numbers keys as they come, from `first`; `new` holds those that came since it was last emptied."""

    def __init__(self, first: int = 0):
        super().__init__()
        self.first, self.new = first, []

    def __missing__(self, key):
        at = self[key] = self.first + len(self)
        self.new.append(key)
        return at


class WordCoder:
    """Encodes words in one worker. Row w of `ids` and of `raw` holds the ids and the decoded bytes of the word numbered w.

    The rows of `piece_ids` and `piece_raw` are the vocabulary's tokens, then the pieces met so far.
    """

    def __init__(self, ranks: dict[bytes, int], merges: pa.Table):
        import duckdb

        self.token_at = {token: at for at, token in enumerate(ranks)}
        self.tokens, self.token_ids = list(ranks), np.array(list(ranks.values()), np.int64)
        self.db = duckdb.connect(config={"threads": 1, "memory_limit": "300MB", "temp_directory": ""})
        self.db.register("merges_given", merges)
        self.db.execute("CREATE TABLE merges AS SELECT * FROM merges_given")
        self.db.register("vocab_given", pa.table({"tok": self.token_ids, "hex": [t.hex() for t in ranks]}))
        self.db.execute("CREATE TABLE vocab AS SELECT * FROM vocab_given")
        self.bytes_of = np.array([ranks[bytes([b])] for b in range(256)], np.int64)
        #: Two-byte tokens, and three-byte runs that some token holds.
        self.two, three = np.zeros(1 << 16, bool), np.zeros(1 << 24, bool)
        for token in ranks:
            if len(token) == 2:
                self.two[token[0] << 8 | token[1]] = True
            for k in range(len(token) - 2):
                three[token[k] << 16 | token[k + 1] << 8 | token[k + 2]] = True
        self.three = np.packbits(three, bitorder="little")
        self.forget_pieces()
        self.forget_words()

    def forget_words(self) -> None:
        self.words, self.ids, self.raw = Numbered(), Ragged(np.uint16), Ragged(np.uint8)

    def forget_pieces(self) -> None:
        self.pieces, self.piece_ids, self.piece_raw = Numbered(len(self.tokens)), Ragged(np.uint16), Ragged(np.uint8)
        self.piece_ids.append(self.token_ids, np.ones(len(self.tokens), np.int64))
        self.piece_raw.append(np.frombuffer(b"".join(self.tokens), np.uint8), np.array([len(t) for t in self.tokens]))

    def encode(self, words: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Ids and decoded bytes of the words one after the other, and the numbers of ids and of bytes of each word."""
        if len(self.words) > WORDS_KEPT:
            self.forget_words()
        at = np.fromiter(map(self.words.__getitem__, words), np.int64, len(words))
        if self.words.new:
            self.learn(self.words.new)
            self.words.new = []
        return *self.ids.take(at), *self.raw.take(at)

    def learn(self, words: list[str]) -> None:
        """Append the rows of words that were numbered just now."""
        if len(self.pieces) > PIECES_KEPT:
            self.forget_pieces()
        raw = [w.encode() for w in words]
        whole = [self.token_at.get(r, -1) for r in raw]
        hard = [r for r, at in zip(raw, whole, strict=True) if at < 0 and r]
        cut, parts = self.cut(hard)
        rows = np.fromiter((self.token_at[p] if len(p) == 1 else self.pieces[p] for p in cut), np.int64, len(cut))
        if self.pieces.new:
            self._merge(self.pieces.new)
            self.pieces.new = []
        counts = np.array([0 if not r else at >= 0 for r, at in zip(raw, whole, strict=True)], np.int64)
        split = np.array([at < 0 and r != b"" for r, at in zip(raw, whole, strict=True)], bool)
        counts[split] = parts
        entries = np.empty(int(counts.sum()), np.int64)
        in_split = np.repeat(split, counts)
        entries[in_split] = rows
        entries[~in_split] = [at for at in whole if at >= 0]
        for store, of in ((self.ids, self.piece_ids), (self.raw, self.piece_raw)):
            flat, sizes = of.take(entries)
            run = np.append(0, np.cumsum(sizes))
            ends = np.cumsum(counts)
            store.append(flat, run[ends] - run[ends - counts])

    def cut(self, words: list[bytes]) -> tuple[list[bytes], np.ndarray]:
        """The pieces of all words, in order, and how many each word has.

        A token across the cut between bytes b and c is the token bc, or it holds c after the two bytes ab, or b before cd.
        """
        joined = b"".join(words)
        n, sizes = len(joined), np.array([len(w) for w in words], np.int64)
        if not n:
            return [], np.zeros(len(words), np.int64)
        buf = np.frombuffer(joined, np.uint8).astype(np.int32)
        first = np.cumsum(sizes) - sizes
        inside, crossed = np.ones(n, bool), np.zeros(n, bool)  # of the cut before each byte
        inside[first] = False
        pair = np.append(0, buf[:-1] << 8 | buf[1:])
        crossed[1:] = self.two[pair[1:]]
        three = pair[1:-1] << 8 | buf[2:]
        held = (self.three[three >> 3] >> (three & 7) & 1).astype(bool) & inside[1:-1] & inside[2:]
        crossed[1:-1] |= held
        crossed[2:] |= held
        heads = np.flatnonzero(~(crossed & inside))
        edges = [*heads.tolist(), n]
        return [joined[a:b] for a, b in zip(edges, edges[1:], strict=False)], np.diff(np.searchsorted(heads, np.append(first, n)))

    def _merge(self, pieces: list[bytes]) -> None:
        """Append the rows of new pieces."""
        found: list[tuple[np.ndarray, np.ndarray, bytes, np.ndarray]] = []  # ids, their numbers, bytes, their numbers
        order = np.argsort([len(p) for p in pieces], kind="stable")  # pieces of like length need like numbers of rounds
        at = 0
        while at < len(order):
            end, size = at, 0
            long = len(pieces[order[at]]) > SHORT
            while end < len(order) and end - at < PIECES and (end == at or size + len(pieces[order[end]]) <= BYTES) and (len(pieces[order[end]]) > SHORT) == long:
                size += len(pieces[order[end]])
                end += 1
            batch = [pieces[k] for k in order[at:end]]
            found.append(self._long(batch) if long else self._short(batch))
            at = end
        back = np.empty(len(order), np.int64)
        back[order] = np.arange(len(order))
        for store, flats, sizes in ((self.piece_ids, [f[0] for f in found], [f[1] for f in found]), (self.piece_raw, [np.frombuffer(f[2], np.uint8) for f in found], [f[3] for f in found])):
            size = np.concatenate(sizes)
            store.append(_ragged(np.concatenate(flats), (np.cumsum(size) - size)[back], size[back]), size[back])
        release()

    def _rows(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        sizes = np.array([len(p) for p in pieces])
        pos = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        return np.repeat(np.arange(len(pieces)), sizes), pos, self.bytes_of[np.frombuffer(b"".join(pieces), np.uint8)]

    def _short(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, bytes, np.ndarray]:
        piece, pos, tok = self._rows(pieces)
        self.db.register("start", pa.table({"piece": piece, "pos": pos, "tok": tok, "nxt": pos + 1}))
        for aggregates in (IN_ORDER, ORDERED):
            got = self.db.sql(MERGE_SQL.format(aggregates=aggregates)).to_arrow_table().combine_chunks().sort_by("piece").combine_chunks()
            places = got["places"].chunk(0)
            starts = np.zeros(len(places.flatten()) + 1, bool)
            starts[np.cumsum(places.value_lengths().to_numpy())] = True
            if ((np.diff(places.flatten().to_numpy()) > 0) | starts[1:-1]).all():
                break
        self.db.unregister("start")
        ids, decoded = got["ids"].chunk(0), got["decoded"].to_pylist()
        return ids.flatten().to_numpy(), ids.value_lengths().to_numpy(), bytes.fromhex("".join(decoded)), np.array([len(d) // 2 for d in decoded])

    def _long(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, bytes, np.ndarray]:
        done: dict[int, tuple[np.ndarray, str]] = {}
        piece, pos, tok = self._rows(pieces)
        low = np.full(len(piece), -1)
        while len(piece):
            rounds = max(1, LONG_ROWS // len(piece))
            self.db.register("start", pa.table({"piece": piece, "pos": pos, "tok": tok, "low": low}))
            got = self.db.sql(LONG_SQL, params={"rounds": rounds}).to_arrow_table().to_pylist()
            self.db.unregister("start")
            left = []
            for r in got:
                if r["fell"]:
                    ids, _, body, _ = self._short([pieces[r["piece"]]])
                    done[r["piece"]] = ids, body.hex()
                elif r["round"] < rounds:
                    done[r["piece"]] = np.array(r["ids"]), r["decoded"]
                else:
                    left.append(r)
            sizes = np.array([len(r["ids"]) for r in left], np.int64)
            piece, low = (np.repeat(np.array([r[c] for r in left], np.int64), sizes) for c in ("piece", "low"))
            pos = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            tok = np.array([i for r in left for i in r["ids"]], np.int64)
        out = [done[k] for k in range(len(pieces))]
        return np.concatenate([i for i, _ in out]), np.array([len(i) for i, _ in out]), bytes.fromhex("".join(d for _, d in out)), np.array([len(d) // 2 for _, d in out])


def _coder(mark: int, shared) -> WordCoder:
    """The worker's coder, kept from task to task."""
    if KEPT.get("bpe", (None,))[0] != mark:
        ranks, keys, merged = shared.value
        KEPT["bpe"] = mark, WordCoder(ranks, pa.table({"key": keys, "rank": merged}))
    return KEPT["bpe"][1]


def _shared(df: DataFrame, ranks_path: str):
    """The vocabulary's size is fixed by the tokenizer (ids below 65536), so it is broadcast."""
    ranks = read_ranks(ranks_path)
    merges = merge_table(ranks)
    keys, merged = merges["key"].to_numpy(), merges["rank"].to_numpy()
    mark = zlib.crc32(b"\n".join(ranks), zlib.crc32(np.array(list(ranks.values())).tobytes()))
    return mark, df.sparkSession.sparkContext.broadcast((ranks, keys, merged))


def encode(df: DataFrame, ranks_path: str, pattern: str, doc_id: str = "doc_id", text: str = "text", digests: bool = False, keep: tuple[str, ...] = ()) -> DataFrame:
    """Encode every whole text and decode it again.

    ids: array<int>; decoded: the decoded bytes as text. With digests=True the row has n_tokens and the
    SHA-256 digests of both instead, so that long texts don't leave the worker. `keep` names further columns to pass on.
    """
    mark, shared = _shared(df, ranks_path)
    tail = "n_tokens long, ids_sha256 string, decoded_sha256 string" if digests else "n_tokens long, ids array<int>, decoded string"
    names = [f.split()[0] for f in tail.split(", ")]
    kinds = (pa.string(), pa.string()) if digests else (pa.list_(pa.int32()), pa.string())

    def blocks(texts: list[str], cutter) -> Iterator[tuple[int, list[str]]]:
        """Words of each text, long texts in several blocks."""
        for k, t in enumerate(texts):
            if len(t) <= TOGETHER:
                yield k, cutter(t).findall(t)
            else:
                words = (m.group() for m in cutter(t).finditer(t))
                while block := list(islice(words, TOGETHER)):
                    yield k, block

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import regex

        wide, narrow = regex.compile(pattern), latin_pattern(pattern)

        def cutter(t: str):
            if narrow is None:
                return wide
            if not t.isascii():
                try:
                    t.encode("latin-1")
                except UnicodeEncodeError:
                    return wide
            return narrow

        coder = None
        for batch in batches:
            for piece in slices(batch, "text"):
                coder = coder or _coder(mark, shared)
                texts = [t or "" for t in piece.column("text").to_pylist()]
                n = [0] * len(texts)
                held: list = [(hashlib.sha256(), hashlib.sha256()) if digests else ([], []) for _ in texts]
                waiting: list[tuple[int, list[str]]] = []

                def settle(n=n, held=held, waiting=waiting, coder=coder) -> None:
                    counts = np.array([len(w) for _, w in waiting])
                    ids, sizes, raw, lengths = coder.encode(list(chain.from_iterable(w for _, w in waiting)))
                    ends = np.cumsum(counts)
                    of_ids, of_raw = (np.append(0, np.cumsum(s)) for s in (sizes, lengths))
                    for (k, _), a, b in zip(waiting, (ends - counts).tolist(), ends.tolist(), strict=True):
                        mine, body = ids[of_ids[a] : of_ids[b]], raw[of_raw[a] : of_raw[b]].tobytes()
                        n[k] += len(mine)
                        if digests:
                            held[k][0].update(mine.astype("<u4").tobytes())
                            held[k][1].update(body)
                        else:
                            held[k][0].append(mine.astype("<i4"))
                            held[k][1].append(body)
                    waiting.clear()

                size = 0
                for k, words in blocks(texts, cutter):
                    waiting.append((k, words))
                    size += len(words)
                    if size >= TOGETHER:
                        settle()
                        size = 0
                if waiting:
                    settle()
                a = [h[0].hexdigest() if digests else np.concatenate(h[0]) if h[0] else [] for h in held]
                b = [h[1].hexdigest() if digests else b"".join(h[1]).decode() for h in held]
                kept = [piece.column(f"k{i}") for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([piece.column("key"), *kept, pa.array(n, pa.int64()), pa.array(a, kinds[0]), pa.array(b, kinds[1])], ["key", *(f"k{i}" for i in range(len(keep))), *names])
        release()

    kind = df.schema[doc_id].dataType.simpleString()
    given = df.select(F.col(doc_id).alias("key"), F.col(text).cast("string").alias("text"), *(F.col(c).alias(f"k{i}") for i, c in enumerate(keep)))
    more = "".join(f"k{i} {df.schema[c].dataType.simpleString()}, " for i, c in enumerate(keep))
    small_batches(df.sparkSession)
    out = given.mapInArrow(run, f"key {kind}, {more}{tail}")
    return out.select(F.col("key").alias(doc_id), *(F.col(f"k{i}").alias(c) for i, c in enumerate(keep)), *names)


def decode(df: DataFrame, ranks_path: str, doc_id: str = "doc_id", ids: str = "ids") -> DataFrame:
    """Texts of id lists: the pieces of each row joined with the vocabulary and aggregated in order of position.

    A null list decodes as the empty text; bytes that are not UTF-8 become the replacement character; an id
    that is not in the vocabulary raises ValueError.
    """
    mark, shared = _shared(df, ranks_path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = None
        for batch in batches:
            coder = coder or _coder(mark, shared)
            for at in range(0, batch.num_rows, 256):
                piece = batch.slice(at, 256)
                lists = [x or [] for x in piece.column("ids").to_pylist()]
                sizes = np.array([len(x) for x in lists], np.int64)
                flat = np.array([i for x in lists for i in x], np.int64)
                if flat.size and not np.isin(flat, coder.token_ids).all():
                    raise ValueError("an id is not in the vocabulary")
                pos = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                coder.db.register("pieces", pa.table({"row": np.repeat(np.arange(len(lists)), sizes), "pos": pos, "tok": flat}))
                got = dict(coder.db.execute(DECODE_SQL).fetchall())
                coder.db.unregister("pieces")
                yield pa.RecordBatch.from_arrays([piece.column("key"), pa.array([bytes.fromhex(got.get(k, "")).decode(errors="replace") for k in range(len(lists))], pa.string())], ["key", "text"])

    kind = df.schema[doc_id].dataType.simpleString()
    return df.select(F.col(doc_id).alias("key"), F.col(ids).cast("array<int>").alias("ids")).mapInArrow(run, f"key {kind}, text string").withColumnRenamed("key", doc_id)
