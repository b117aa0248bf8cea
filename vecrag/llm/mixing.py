"""Temperature mixing of sources, realised as budgeted block permutations.

With token shares p of the sources, the mixed weights are p^x / sum(p^x). The exponent x is bisected so that the
weights' entropy reaches a share of the largest possible one, but never below the x at which some source would be
repeated more often than the repetition limit allows. A source's budget is its weight times the total budget: whole
passes over the source, then a last partial pass. A pass is a permutation of the source's blocks: each row falls
into a block by a hash of (seed, pass, id), blocks follow each other, and rows inside a block are ordered by the
same hash. The partial pass takes rows until the budget is met; only its one cut block needs an order of rows, so
no task ever holds a source.

Every row that is taken says where it stands: its pass, its block, the block's turn in the pass (0 to 1) and its place;
`in_order` writes rows by them, so that the sources alternate and each pass is a permutation.

Defined results: a null source is a source of its own; null or empty texts have 0 tokens and go with every pass (they
cost nothing); repeated rows are rows of their own, but rows equal in both id and text share one place, so a partial pass
takes all of them or none; an empty table gives an empty table. The result has the columns of the table and the four
marks, with a row for each pass that takes it; a mark whose name the table uses already gets a trailing underscore.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecrag.llm.common import checkpointed, numbered

#: Production parameters: entropy as a share of the largest, passes over one source, rows of a block on average.
ENTROPY, REPEATS, BLOCK_ROWS, SEED = 0.95, 2.0, 1000, 42
#: Sources whose plans (under 100 bytes each) come to the driver and are broadcast; beyond, the exponent is found by
#: aggregates over the table of sources, GRID exponents a job, and rows and plans are shuffled.
BROADCAST_SOURCES, GRID = 100_000, 16
MARKS = ("pass_no", "block_no", "turn", "place")


def weights(tokens: np.ndarray, exponent: float) -> np.ndarray:
    """Normalised p^x; sources without tokens weigh nothing."""
    p = np.asarray(tokens, float)
    if not p.sum():
        return np.zeros(len(p))
    with np.errstate(divide="ignore"):
        logs = np.where(p > 0, exponent * np.log(p / p.sum()), -np.inf)
    w = np.exp(logs - logs.max())
    return w / w.sum()


def entropy(w: np.ndarray) -> float:
    w = w[w > 0]
    return float(-(w * np.log(w)).sum()) + 0.0


def _bisect(low: float, high: float, ok, steps: int = 60) -> float:
    """The end of [low, high] where ok turns true, ok(high) given."""
    for _ in range(steps):
        mid = (low + high) / 2
        low, high = (low, mid) if ok(mid) else (mid, high)
    return high


def solve_exponent(tokens: np.ndarray, budget: float, target: float | None = ENTROPY, repeats: float | None = REPEATS) -> float:
    """The largest exponent in [0, 1] whose entropy reaches `target` * ln(sources), raised as far as `repeats` asks.

    Without a target it is the smallest that `repeats` allows; without either it is 1.

    Entropy falls and the most-repeated source's passes fall as x rises from 0 (all sources alike) to 1 (as they are).
    """
    tokens = np.asarray(tokens, float)
    live = tokens[tokens > 0]
    if len(live) < 2:
        return 1.0
    by_entropy = 1.0 if target is not None or repeats is None else 0.0
    if target is not None and entropy(weights(live, 1.0)) < target * math.log(len(live)):
        by_entropy = 1 - _bisect(0.0, 1.0, lambda y: entropy(weights(live, 1 - y)) >= target * math.log(len(live)))
    by_repeats = 0.0
    if repeats is not None:
        most = lambda x: (weights(live, x) * budget / live).max()
        if most(1.0) > repeats:
            raise ValueError(f"a budget of {budget:g} tokens needs more than {repeats:g} passes in any mixture")
        if most(0.0) > repeats:
            by_repeats = _bisect(0.0, 1.0, lambda x: most(x) <= repeats)
    return max(by_entropy, by_repeats)


def _counted(text: Column) -> Column:
    """Words between white space; 0 for null."""
    return F.coalesce(F.regexp_count(text.cast("string"), F.lit(r"\S+")), F.lit(0)).cast("long")


def plan(totals: list[tuple], budget: float | None, target: float | None, repeats: float | None) -> list[tuple]:
    """(source, weight, full passes, tokens of the partial pass) of each (source, tokens)."""
    tokens = np.array([t for _, t in totals], float)
    budget = float(tokens.sum()) if budget is None else float(budget)
    x = solve_exponent(tokens, budget, target, repeats)
    out = []
    for (source, size), w in zip(totals, weights(tokens, x), strict=True):
        passes, rest = divmod(w * budget, size) if size else (1.0, 0.0)
        if size and size - rest < 1e-6 * size:  # a whole pass but for rounding
            passes, rest = passes + 1, 0.0
        out.append((source, float(w), int(passes), float(rest) if rest > 1e-6 * size else 0.0))
    return out


def _grid(live: DataFrame, total: float, budget: float, xs: list[float]) -> list[tuple[float, float]]:
    """(entropy, most passes over one source) at each exponent, by one aggregate over the sources with tokens."""
    p = F.col("tokens") / F.lit(float(total))
    each = [c for x in xs for c in (F.sum(F.pow(p, F.lit(x))), F.sum(F.pow(p, F.lit(x)) * F.log(p)), F.max(F.pow(p, F.lit(x)) / F.col("tokens")))]
    row = live.agg(*(c.alias(f"g{k}") for k, c in enumerate(each))).first()
    return [(math.log(row[3 * k]) - x * row[3 * k + 1] / row[3 * k], budget * row[3 * k + 2] / row[3 * k]) for k, x in enumerate(xs)]


def solve_distributed(totals: DataFrame, budget: float, target: float | None, repeats: float | None) -> float:
    """solve_exponent over a table of any number of sources (tokens): brackets are narrowed GRID-fold by each job."""
    live = totals.where("tokens > 0").select(F.col("tokens").cast("double").alias("tokens"))
    n, total = live.agg(F.count("*"), F.sum("tokens")).first()
    if n < 2:
        return 1.0
    (flat, worst_flat), (own, worst_own) = _grid(live, total, budget, [0.0, 1.0])
    if repeats is not None and worst_own > repeats:
        raise ValueError(f"a budget of {budget:g} tokens needs more than {repeats:g} passes in any mixture")
    wanted = -math.inf if target is None else target * math.log(n)

    def edge(ok: Callable[[tuple[float, float]], bool], rising: bool) -> float:
        """Where ok turns along the exponents: the largest x that is ok, or, if `rising`, the smallest."""
        low, high = 0.0, 1.0
        while high - low > 1e-13:
            xs = [low + (high - low) * k / GRID for k in range(GRID + 1)]
            fits = [ok(g) for g in _grid(live, total, budget, xs)]
            k = next(i for i in range(GRID) if fits[i] != fits[i + 1])
            low, high = xs[k], xs[k + 1]
        return high if rising else low

    by_entropy = 1.0 if target is not None or repeats is None else 0.0
    if target is not None and own < wanted:
        by_entropy = edge(lambda g: g[0] >= wanted, False) if flat >= wanted else 0.0
    by_repeats = edge(lambda g: g[1] <= repeats, True) if repeats is not None and worst_flat > repeats else 0.0
    return max(by_entropy, by_repeats)


def _plans(totals: DataFrame, budget: float | None, target: float | None, repeats: float | None) -> tuple[DataFrame, bool]:
    """(source, weight, full passes, tokens of the partial pass, blocks) of each source, and whether they may be broadcast."""
    n, total = totals.agg(F.count("*"), F.coalesce(F.sum("tokens"), F.lit(0))).first()
    blocks = F.greatest(F.lit(1), F.ceil(F.col("n") / BLOCK_ROWS)).cast("long").alias("blocks")
    if n <= BROADCAST_SOURCES:
        planned = plan([(r["s"], r["tokens"]) for r in totals.orderBy("s").collect()], budget, target, repeats)
        table = totals.sparkSession.createDataFrame([(s, w, p, rest) for s, w, p, rest in planned], "s string, w double, p int, rest double")
        return table.join(totals.select("s", blocks), "s"), True
    budget = float(total) if budget is None else float(budget)
    x = solve_distributed(totals, budget, target, repeats)
    mass = totals.where("tokens > 0").agg(F.sum(F.pow(F.col("tokens") / F.lit(float(total)), F.lit(x)))).first()[0]
    w = F.when(F.col("tokens") > 0, F.pow(F.col("tokens") / F.lit(float(total)), F.lit(x)) / F.lit(mass)).otherwise(F.lit(0.0))
    share = F.col("w") * F.lit(budget) / F.col("tokens")
    whole = F.floor(share + 1e-6)  # a whole pass but for rounding
    rest = F.greatest(share - whole, F.lit(0.0)) * F.col("tokens")
    out = totals.withColumn("w", w).select("s", "w", F.when(F.col("tokens") > 0, whole).otherwise(1).cast("int").alias("p"), F.when((F.col("tokens") > 0) & (share - whole > 1e-6), rest).otherwise(F.lit(0.0)).alias("rest"), blocks)
    return out, False


def mix(df: DataFrame, doc_id: str = "doc_id", text: str = "text", source: str = "source", budget: float | None = None, target: float | None = ENTROPY, repeats: float | None = REPEATS, seed: int = SEED) -> DataFrame:
    """Rows of `df` by the budgets of their sources, with pass_no (from 0), block_no, turn and place."""
    given, _ = numbered(df)
    of_id, of_text, of_source = (F.col(f"c{df.columns.index(c)}") for c in (doc_id, text, source))
    key = F.coalesce(F.concat(F.lit("="), of_source.cast("string")), F.lit("null"))
    own = [key.alias("s"), F.xxhash64(of_id, of_text).alias("id"), _counted(of_text).alias("t")]
    rows = checkpointed(given.select(*own))
    totals = checkpointed(rows.groupBy("s").agg(F.sum("t").alias("tokens"), F.count("*").alias("n")))
    plans, few = _plans(totals, budget, target, repeats)
    plans = checkpointed(plans)
    small = F.broadcast if few else lambda table: table
    place_of = lambda turn: F.xxhash64(F.lit(seed), turn, F.col("id"))
    block_of = lambda place: F.pmod(F.shiftright(place, 20), F.col("blocks"))
    place = place_of(F.col("p"))
    # the partial pass: prefix sums over blocks, then over the rows of the one block that the budget cuts
    last = rows.join(small(plans.where("rest > 0")), "s").withColumn("place", place).withColumn("block", block_of(F.col("place")))
    sums = last.groupBy("s", "block").agg(F.sum("t").alias("bt"), F.first("rest").alias("rest"))
    before = checkpointed(_running(sums))
    cuts = before.where("start < rest and start + bt >= rest").groupBy("s").agg(F.min(F.struct("block", "start")).alias("c")).select("s", "c.*")
    inside = last.join(small(cuts), ["s", "block"]).groupBy("s", "block", "place").agg(F.sum("t").alias("bt"), F.first("rest").alias("rest"), F.first("start").alias("from"))
    edge = _last_place(inside)
    limits = checkpointed(plans.join(cuts.select("s", F.col("block").alias("cut")), "s", "left").join(edge, "s", "left"))
    # every row meets its source's plan: one row a source, broadcast as long as there are few enough
    out = given.select("*", *own).join(small(limits), "s").withColumn("place", place).withColumn("block", block_of(F.col("place")))
    partial = (F.col("rest") > 0) & ((F.col("t") == 0) | F.col("cut").isNull() | (F.col("block") < F.col("cut")) | ((F.col("block") == F.col("cut")) & (F.col("place") <= F.col("edge"))))
    copies = F.col("p") + F.when(partial, 1).otherwise(0)
    out = out.withColumn("turns", copies).where("turns > 0").withColumn("pass", F.explode(F.sequence(F.lit(0), F.col("turns") - 1)))
    out = out.withColumn("place", place_of(F.col("pass"))).withColumn("block", block_of(F.col("place")))
    turn = (F.col("block") + 0.5) / F.col("blocks")
    marks = dict(zip(MARKS, (F.col("pass").cast("int"), F.col("block"), turn, F.col("place")), strict=True))
    return out.select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(df.columns)), *(marks[m].alias(name) for m, name in mark_names(df.columns).items()))


def mark_names(columns: list[str]) -> dict[str, str]:
    """Names of the marks beside the given columns."""
    out = {}
    for mark in MARKS:
        name = mark
        while name in columns:
            name += "_"
        out[mark] = name
    return out


def in_order(mixed: DataFrame, columns: list[str]) -> DataFrame:
    """The rows of mix() in the order of pass, turn and place, over all files that are written; marks dropped."""
    p, _, turn, place = (F.col(f"`{c}`") for c in mark_names(columns).values())
    return mixed.repartitionByRange(p, turn, place).sortWithinPartitions(p, turn, place).select(*(F.col(f"`{c}`") for c in columns))


def _running(sums: DataFrame) -> DataFrame:
    """Tokens before each block of its source (`start`).

    A source has rows / BLOCK_ROWS blocks; prefix sums of that many rows are made in two levels, in groups of 1000.
    """
    from pyspark.sql import Window as W

    sums = sums.withColumn("group", F.floor(F.col("block") / 1000))
    groups = sums.groupBy("s", "group").agg(F.sum("bt").alias("gt"))
    groups = groups.withColumn("gstart", F.sum("gt").over(W.partitionBy("s").orderBy("group").rowsBetween(W.unboundedPreceding, -1)))
    inner = F.sum("bt").over(W.partitionBy("s", "group").orderBy("block").rowsBetween(W.unboundedPreceding, -1))
    out = sums.withColumn("inner", F.coalesce(inner, F.lit(0))).join(groups.select("s", "group", F.coalesce("gstart", F.lit(0)).alias("gstart")), ["s", "group"])
    return out.select("s", "block", "bt", "rest", (F.col("gstart") + F.col("inner")).alias("start"))


def _last_place(inside: DataFrame) -> DataFrame:
    """Place of the row with which the cut block meets the budget, for each source: rows after it stay out."""
    from pyspark.sql import Window as W

    run = F.sum("bt").over(W.partitionBy("s", "block").orderBy("place").rowsBetween(W.unboundedPreceding, -1))
    met = inside.withColumn("run", F.col("from") + F.coalesce(run, F.lit(0)))
    return met.where("run < rest").groupBy("s").agg(F.max("place").alias("edge"))
