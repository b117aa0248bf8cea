"""Analytical models of memory, time and energy: Column arithmetic over a table of parameters.

A parameter row has N, d, Nc, M, M2 (links of the centroid graph), m_pq, nbits, nP, ef_H, ef_c, ef_L as doubles or
longs. The modelled device numbers are never to be mixed with measured times of a cluster.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Methods in the order of the published comparison.
METHODS = ("ivf", "ivfpq", "graph", "graph_pq", "ivf_disk", "ivfpq_disk", "ivf_graph", "two_tier")
PARAMETERS = "name string, N double, d double, Nc double, M double, M2 double, m_pq double, nbits double, nP double, ef_H double, ef_c double, ef_L double"
#: Device constants as published (fixed values).
T_OP_MS, SEEK_MS, COMMAND_MS, BYTE_MS = 1.94e-4, 0.025, 0.015, 3.6e-7
VOLT, CPU_UA, DISK_UA = 4.0, 2300.0, 800.0
#: Shapes of the two published vector sets and of the given table.
SHAPES = (
    ("published", 1e6, 128.0, 4000.0, 32.0, 16.0, 16.0, 8.0, 16.0, 128.0, 32.0, 16.0),
    ("published_256", 2.9e5, 256.0, 1160.0, 32.0, 16.0, 32.0, 8.0, 16.0, 128.0, 32.0, 16.0),
    ("small", 500.0, 64.0, 16.0, 16.0, 8.0, 8.0, 8.0, 4.0, 64.0, 16.0, 16.0),
)


def parameters(spark: SparkSession, rows=SHAPES) -> DataFrame:
    return spark.createDataFrame([tuple(r) for r in rows], PARAMETERS)


def _c(name: str) -> Column:
    return F.col(name)


def p0(m: Column, mode: str = "printed") -> Column:
    """Chance to reach the next level: 1 / ln M as printed, 1 / M as levels are drawn."""
    if mode == "printed":
        return F.lit(1.0) / F.log(m)
    if mode == "geometric":
        return F.lit(1.0) / m
    raise ValueError(f"no such mode: {mode}")


def mem_clustering() -> Column:
    """Bytes of centroids, ids and vectors."""
    return 4 * _c("d") * _c("Nc") + 8 * _c("N") + 4 * _c("d") * _c("N")


def mem_links(n: Column, m: Column, chance: Column, level: Column | int) -> Column:
    """Bytes of 4-byte links on one level."""
    return 4 * n * m * F.pow(chance, F.lit(level) if isinstance(level, int) else level)


def mem_links_total(n: Column, m: Column, chance: Column, levels: int | None = None) -> Column:
    """Links of all levels: the infinite geometric sum, or levels 0..levels-1."""
    if levels is None:
        return 4 * n * m / (1 - chance)
    return F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(levels - 1)), lambda k: 4 * n * m * F.pow(chance, k)), F.lit(0.0), lambda s, x: s + x)


def mem_graph(n: Column, m: Column, chance: Column) -> Column:
    """Links and vectors of a graph (4-byte coordinates)."""
    return mem_links_total(n, m, chance) + 4 * _c("d") * n


def mem_codes() -> Column:
    """Codes of all vectors and the codebook."""
    return _c("N") * _c("m_pq") * _c("nbits") / 8 + F.pow(F.lit(2.0), _c("nbits")) * 4 * _c("d")


def memory_model(params: DataFrame, as_printed: bool = True, resident: str = "one_vector", p0_mode: str = "printed") -> DataFrame:
    """(name, method, bytes): the eight methods' resident memory.

    as_printed keeps the printed factor 4 on the links of the graph with codes. resident says what a disk method keeps
    of its lists: one vector or node, as printed, or one whole list.
    """
    if resident not in ("one_vector", "one_list"):
        raise ValueError(f"no such form: {resident}")
    n, d, nc, m, m2 = _c("N"), _c("d"), _c("Nc"), _c("M"), _c("M2")
    held = F.lit(1.0) if resident == "one_vector" else n / nc
    links, links2 = 4 * m / (1 - p0(m, p0_mode)), 4 * m2 / (1 - p0(m2, p0_mode))
    code, book = _c("m_pq") * _c("nbits") / 8, F.pow(F.lit(2.0), _c("nbits")) * 4 * d
    lists, centre = 4 * d * nc + 8 * n, nc * (4 * d + links2) + 8 * n
    forms = {
        "ivf": lists + 4 * d * n,
        "ivfpq": lists + n * code + book,
        "graph": n * (4 * d + links),
        "graph_pq": n * (code + links * (4 if as_printed else 1)) + book,
        "ivf_disk": lists + 4 * d * held,
        "ivfpq_disk": lists + code * held + book,
        "ivf_graph": centre + 4 * d * held,
        "two_tier": centre + (4 * d + links2) * held,
    }
    return _by_method(params, forms, "bytes")


def _by_method(params: DataFrame, forms: dict[str, Column], value: str) -> DataFrame:
    """One row for each parameter row and method."""
    rows = F.array(*(F.struct(F.lit(k).alias("method"), forms[k].cast("double").alias(value)) for k in METHODS))
    return params.select("name", F.explode(rows).alias("x")).select("name", "x.method", f"x.{value}")


def ops_model(params: DataFrame) -> DataFrame:
    """(name, method, ops): distance computations of one search."""
    nc, scan = _c("Nc"), _c("nP") * _c("N") / _c("Nc")
    coded = _c("m_pq") / _c("d") * _c("nbits") / 8
    table = F.pow(F.lit(2.0), _c("nbits"))
    graph, centre = _c("ef_H") * _c("M"), _c("ef_c") * _c("M2")
    forms = {
        "ivf": nc + scan, "ivfpq": nc + scan * coded + table, "graph": graph, "graph_pq": graph * coded + table,
        "ivf_disk": nc + scan, "ivfpq_disk": nc + scan * coded + table, "ivf_graph": centre + scan, "two_tier": centre + _c("nP") * _c("ef_L") * _c("M2"),
    }
    return _by_method(params, forms, "ops")


def t_op_ms(cycles: float = 500.0, hz: float = 2.4e9) -> float:
    """Milliseconds of one distance."""
    return cycles / hz * 1000


def disk_ms(seeks: Column, size: Column, seek: float = SEEK_MS, command: float = COMMAND_MS, per_byte: float = BYTE_MS) -> Column:
    return seeks * (seek + command + size * per_byte)


def latency_model(params: DataFrame, t_op: float = T_OP_MS, p0_mode: str = "printed") -> DataFrame:
    """(name, method, t_s, t_d, ms): computing time, disk time (one seek and list for each probe) and their sum."""
    per_list = _c("N") / _c("Nc")
    links2 = 4 * _c("M2") / (1 - p0(_c("M2"), p0_mode))
    size = {
        "ivf_disk": per_list * (4 * _c("d") + 8), "ivfpq_disk": per_list * (_c("m_pq") * _c("nbits") / 8 + 8),
        "ivf_graph": per_list * (4 * _c("d") + 8), "two_tier": per_list * (4 * _c("d") + links2 + 8),
    }
    disk = _by_method(params, {k: disk_ms(_c("nP"), size[k]) if k in size else F.lit(0.0) for k in METHODS}, "t_d")
    times = ops_model(params).join(disk, ["name", "method"])
    t_s = F.col("ops") * t_op
    return times.select("name", "method", t_s.alias("t_s"), "t_d", (t_s + F.col("t_d")).alias("ms"))


def energy_model(latency: DataFrame, volt: float = VOLT, cpu_ua: float = CPU_UA, disk_ua: float = DISK_UA) -> DataFrame:
    """(name, method, uj): V (I_s t_s + I_d t_d) in microjoules, for times in ms and currents in microampere."""
    return latency.select("name", "method", (volt * (cpu_ua * F.col("t_s") + disk_ua * F.col("t_d")) / 1000).alias("uj"))


def energy_trace(samples: DataFrame, group: str = "run") -> DataFrame:
    """(group, joule): the trapezoid integral of current (A) x voltage (V) over time (s)."""
    from pyspark.sql import Window as W

    w = W.partitionBy(group).orderBy("t")
    power = F.col("ampere") * F.col("volt")
    area = (power + F.lag(power).over(w)) / 2 * (F.col("t") - F.lag("t").over(w))
    return samples.withColumn("area", area).groupBy(group).agg(F.round(F.sum("area"), 9).alias("joule"))


def break_even(params: DataFrame) -> DataFrame:
    """(name, two_tier_ms, best_list_ms, two_tier_uj, best_list_uj, wins_time, wins_energy): where the claim holds."""
    times = latency_model(params)
    both = times.join(energy_model(times), ["name", "method"])
    of = lambda v, names: F.min(F.when(F.col("method").isin(*names), F.col(v)))
    wide = both.groupBy("name").agg(of("ms", ["two_tier"]).alias("two_tier_ms"), of("ms", ["ivf", "ivf_disk"]).alias("best_list_ms"), of("uj", ["two_tier"]).alias("two_tier_uj"), of("uj", ["ivf", "ivf_disk"]).alias("best_list_uj"))
    return wide.select("name", *(F.round(c, 9).alias(c) for c in wide.columns[1:]), (F.col("two_tier_ms") < F.col("best_list_ms")).alias("wins_time"), (F.col("two_tier_uj") < F.col("best_list_uj")).alias("wins_energy"))


def centroid_sweep(params: DataFrame, n_cs: tuple[int, ...]) -> DataFrame:
    """(name, n_c, bytes, ms, uj) of the two-tier index for several numbers of centroids."""
    grid = params.withColumn("Nc", F.explode(F.array(*(F.lit(float(n)) for n in n_cs)))).withColumn("name", F.concat_ws("@", "name", F.col("Nc").cast("int").cast("string")))
    times = latency_model(grid)
    all_of = memory_model(grid).join(times, ["name", "method"]).join(energy_model(times), ["name", "method"]).where("method = 'two_tier'")
    parts = F.split("name", "@")
    return all_of.select(F.element_at(parts, 1).alias("name"), F.element_at(parts, 2).cast("int").alias("n_c"), F.round("bytes", 3).alias("bytes"), F.round("ms", 9).alias("ms"), F.round("uj", 9).alias("uj"))


def memory_report(index, model: DataFrame | None = None) -> DataFrame:
    """(what, bytes) of a real index: modelled (the two-tier form at its own shape), resident (centroid tier), stored (list
    graphs), the largest list (what a sequential search holds besides) and the share of vectors in it.
    """
    spark, c = index.spark, index.centre
    lists = index.lists.select("n", "dim", "m", (F.length("vecs") + 8 * F.size("ids") + 4 * (F.size("link_to") + F.size("link_ptr") + F.size("levels"))).alias("bytes"))
    total = lists.agg(F.sum("n").alias("N"), F.max("dim").alias("d"), F.max("m").alias("M"), F.sum("bytes").alias("stored"), F.max("bytes").alias("largest_list"))
    resident = len(c["vecs"]) + 8 * len(c["ids"]) + 4 * (len(c["link_to"]) + len(c["link_ptr"]) + len(c["levels"])) + 12 * len(index.radii)
    shape = total.select(F.lit("index").alias("name"), F.col("N").cast("double").alias("N"), F.col("d").cast("double").alias("d"), F.lit(float(c["n"])).alias("Nc"), F.col("M").cast("double").alias("M"), F.lit(float(c["m"])).alias("M2"), *(F.lit(x).alias(n) for n, x in (("m_pq", 8.0), ("nbits", 8.0), ("nP", 4.0), ("ef_H", 64.0), ("ef_c", 32.0), ("ef_L", 32.0))))
    modelled = memory_model(shape, resident="one_list").where("method = 'two_tier'").select(F.lit("modelled").alias("what"), F.round("bytes").cast("long").alias("bytes"))
    real = total.select(F.explode(F.array(*(F.struct(F.lit(n).alias("what"), v.cast("long").alias("bytes")) for n, v in (("resident", F.lit(resident)), ("stored", F.col("stored")), ("largest_list", F.col("largest_list")))))).alias("x")).select("x.what", "x.bytes")
    return modelled.unionByName(real)


def power_report(work: DataFrame, volt: float = VOLT, cpu_ua: float = CPU_UA, disk_ua: float = DISK_UA, t_op: float = T_OP_MS) -> DataFrame:
    """(.., t_s, t_d, uj_model) of counted work (ops, seeks, bytes): modelled computing and disk time in ms, and energy."""
    t_s = F.col("ops") * t_op
    t_d = F.col("seeks") * (SEEK_MS + COMMAND_MS) + F.col("bytes") * BYTE_MS
    return work.select(*work.columns, F.round(t_s, 9).alias("t_s"), F.round(t_d, 9).alias("t_d"), F.round(volt * (cpu_ua * t_s + disk_ua * t_d) / 1000, 9).alias("uj_model"))
