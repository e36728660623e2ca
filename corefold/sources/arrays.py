"""The arrays that experiments run on, from the given tables.

ship4, ship5, trade4v, trade5v, grid5v, pulse4v, vec2, vec4, cube4, skew4, text4, ranked4
and margins; whole-number values stay long.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corefold.functions.tensor import Cells, Chunks, TensorSpec, index_columns
from corefold.sources import synthetic
from corefold.sources.tables import cells_from_table, dictionary, explode_vector, fill_holes, label_index, load_table, unpivot_measures

FLAGS, STATUSES = ["A", "N", "R"], ["F", "O"]
TYPES_LIMIT = 64
MEASURES = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
FIRST_YEAR, YEARS, MONTHS = 1995, 7, 83


def _ship_modes() -> dict:
    return {
        "returnflag": (label_index("l_returnflag", FLAGS), 3),
        "linestatus": (label_index("l_linestatus", STATUSES), 2),
        "month": (F.month("l_shipdate") - 1, 12),
        "linenumber": (F.col("l_linenumber") - 1, 7),
    }


def _quantity() -> F.Column:
    return F.sum(F.col("l_quantity").cast("long"))


def ship4(spark: SparkSession, sf_dir: str) -> Cells:
    return cells_from_table(load_table(spark, sf_dir, "lineitem"), _ship_modes(), _quantity())


def ship5(spark: SparkSession, sf_dir: str) -> Cells:
    modes = _ship_modes() | {"year": (F.year("l_shipdate") - FIRST_YEAR, YEARS)}
    return cells_from_table(load_table(spark, sf_dir, "lineitem"), modes, _quantity())


def _trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines, parts, suppliers = (load_table(spark, sf_dir, t) for t in ("lineitem", "part", "supplier"))
    return lines.join(parts.select(F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey").join(suppliers.select(F.col("s_suppkey").alias("l_suppkey"), "s_nationkey"), "l_suppkey")


def trade4v(spark: SparkSession, sf_dir: str) -> Cells:
    brands = dictionary(load_table(spark, sf_dir, "part"), "p_brand")
    month = ((F.year("l_shipdate") - FIRST_YEAR) * 12 + F.month("l_shipdate") - 1).alias("m")
    rows = unpivot_measures(_trade(spark, sf_dir).withColumn("m", month), ["s_nationkey", "p_brand", "m"], MEASURES)
    modes = {"nation": (F.col("s_nationkey"), 25), "brand": (label_index("p_brand", brands), len(brands)), "measure": (F.col("var"), 4), "month": (F.col("m"), MONTHS)}
    return cells_from_table(rows, modes, F.sum("val"), fill=0.0)


def trade5v(spark: SparkSession, sf_dir: str) -> Cells:
    brands = dictionary(load_table(spark, sf_dir, "part"), "p_brand")
    rows = unpivot_measures(_trade(spark, sf_dir).withColumn("y", F.year("l_shipdate") - FIRST_YEAR), ["s_nationkey", "p_brand", "l_returnflag", "y"], MEASURES)
    modes = {"nation": (F.col("s_nationkey"), 25), "brand": (label_index("p_brand", brands), len(brands)), "returnflag": (label_index("l_returnflag", FLAGS), 3), "measure": (F.col("var"), 4), "year": (F.col("y"), YEARS)}
    return cells_from_table(rows, modes, F.sum("val"), fill=0.0)


def grid5v(spark: SparkSession, sf_dir: str) -> Cells:
    keys = [F.pmod(F.col(f"l_{k}key"), F.lit(10)).cast("int").alias(k) for k in ("supp", "part", "order")]
    lines = load_table(spark, sf_dir, "lineitem").select(*keys, (F.year("l_shipdate") - FIRST_YEAR).alias("y"), *MEASURES)
    rows = unpivot_measures(lines, ["supp", "part", "order", "y"], MEASURES)
    modes = {k: (F.col(k), 10) for k in ("supp", "part", "order")} | {"measure": (F.col("var"), 4), "year": (F.col("y"), YEARS)}
    return cells_from_table(rows, modes, F.sum("val"), fill=0.0)


def pulse4v(spark: SparkSession, sf_dir: str) -> Cells:
    events = load_table(spark, sf_dir, "events")
    types = dictionary(events, "event_type")
    k = F.get_json_object("props", "$.k").cast("double")
    wide = events.select(F.hour("ts").alias("h"), (F.dayofweek("ts") - 1).alias("d"), "event_type", F.lit(1.0).alias("n"), F.col("value").cast("double").alias("value"), k.alias("k"))
    rows = unpivot_measures(wide, ["h", "d", "event_type"], ["n", "value", "k"])
    modes = {"hour": (F.col("h"), 24), "weekday": (F.col("d"), 7), "type": (label_index("event_type", types), len(types)), "variable": (F.col("var"), 3)}
    return cells_from_table(rows, modes, F.sum("val"), fill=0.0)


def vec2(spark: SparkSession, sf_dir: str) -> Cells:
    """Vector by component. The vectors' ids are 0 .. n-1."""
    vectors = load_table(spark, sf_dir, "embeddings")
    n = vectors.agg(F.max("vec_id")).first()[0] + 1
    cells = explode_vector(vectors, "embedding", ids=("vec_id",)).select(F.col("vec_id").cast("int").alias("i_1"), F.col("pos").alias("i_2"), F.col("val").cast("double").alias("v"))
    return Cells(cells, TensorSpec((int(n), 64)))


def vec4(spark: SparkSession, sf_dir: str) -> Cells:
    """Label, the place of a vector within its label, and the components as 8 x 8; zero where a label has fewer vectors than the largest."""
    from pyspark.sql import Window

    vectors = load_table(spark, sf_dir, "embeddings")
    numbered = vectors.withColumn("r", F.row_number().over(Window.partitionBy("label").orderBy("vec_id")) - 1)
    sizes = vectors.groupBy("label").count().agg(F.max("label").alias("last"), F.max("count").alias("most")).first()
    cells = explode_vector(numbered, "embedding", (8, 8), ids=("label", "r"))
    return Cells(cells.select(F.col("label").cast("int").alias("i_1"), F.col("r").cast("int").alias("i_2"), F.col("p_1").alias("i_3"), F.col("p_2").alias("i_4"), F.col("val").cast("double").alias("v")), TensorSpec((int(sizes.last) + 1, int(sizes.most), 8, 8)))


def _keys(dims: tuple[int, int, int, int]) -> list[F.Column]:
    day = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date"))
    columns = [F.col("l_suppkey"), F.col("l_partkey"), F.col("l_orderkey"), day]
    return [F.pmod(c, F.lit(d)) for c, d in zip(columns, dims, strict=True)]


def modular4(spark: SparkSession, sf_dir: str, dims: tuple[int, int, int, int]) -> Cells:
    """Supplier, part and order keys and the day number, each by remainder."""
    modes = {str(i): (c, d) for i, (c, d) in enumerate(zip(_keys(dims), dims, strict=True))}
    return cells_from_table(load_table(spark, sf_dir, "lineitem"), modes, _quantity())


def ranked_factors(spark: SparkSession, sf_dir: str, side: int, rank: int) -> list[np.ndarray]:
    """For each mode of modular4 its sums of quantities by group of orders, a column a group, over the mean of all."""
    keys = _keys((side,) * 4)
    group = F.floor(keys[2] * rank / side).cast("int").alias("g")
    rows = load_table(spark, sf_dir, "lineitem").select(group, F.col("l_quantity").cast("long").alias("q"), F.posexplode(F.array(*[k.cast("int") for k in keys])).alias("mode", "i"))
    factors = np.zeros((4, side, rank))
    for r in rows.groupBy("mode", "i", "g").agg(F.sum("q").alias("q")).collect():  # sides times ranks
        factors[r.mode, r.i, r.g] = r.q
    return list(factors * (side / max(factors[0].sum(), 1)))


def ranked(spark: SparkSession, factors: list[np.ndarray], block: tuple[int, ...] | None = None) -> Chunks:
    """The products of each group's margins, summed over groups: of at most as many ranks in every mode."""
    rank = factors[0].shape[1]
    core = np.zeros((rank,) * len(factors))
    core[(np.arange(rank),) * len(factors)] = 1
    return synthetic.from_factors(spark, core, factors, block)


def ranked4(spark: SparkSession, sf_dir: str, side: int, rank: int, block: tuple[int, ...] | None = None) -> Chunks:
    return ranked(spark, ranked_factors(spark, sf_dir, side, rank), block)


def grid3(spark: SparkSession, sf_dir: str) -> Cells:
    """Supplier, part and order keys by remainder, 4 x 6 x 4."""
    modes = {k: (F.pmod(F.col(f"l_{k}key"), F.lit(d)), d) for k, d in (("supp", 4), ("part", 6), ("order", 4))}
    return cells_from_table(load_table(spark, sf_dir, "lineitem"), modes, _quantity())


def cube4(spark: SparkSession, sf_dir: str, side: int = 10) -> Cells:
    return modular4(spark, sf_dir, (side,) * 4)


def skew4(spark: SparkSession, sf_dir: str) -> Cells:
    return modular4(spark, sf_dir, (5, 50, 50, 50))


def text4(spark: SparkSession, sf_dir: str) -> Cells:
    """Language, source, length bucket and label (0, 1, none): counts. Sparse on purpose."""
    docs, labels = load_table(spark, sf_dir, "documents"), load_table(spark, sf_dir, "labels")
    langs, sources = dictionary(docs, "lang"), dictionary(docs, "source")
    bucket = F.least(F.lit(7), F.floor(F.log2(F.col("n_chars") + 1) / 2))
    joined = docs.select("doc_id", "lang", "source", "n_chars").join(labels.select("doc_id", "quality"), "doc_id", "left")
    modes = {"lang": (label_index("lang", langs), len(langs)), "source": (label_index("source", sources), len(sources)), "length": (bucket, 8), "quality": (F.coalesce("quality", F.lit(2)), 3)}
    return cells_from_table(joined, modes, F.count("*"))


def margins(cells: Cells) -> Cells:
    """The product of an array's one-mode sums: of rank one in every mode. Its four margins are as long as the modes."""
    names = index_columns(cells.spec.order)
    out = None
    for n in names:
        own = cells.df.groupBy(n).agg(F.sum("v").cast("double").alias(f"m_{n}"))
        out = own if out is None else out.crossJoin(F.broadcast(own))
    total = F.sum("v").cast("double")
    whole = cells.df.agg(total.alias("t"))
    product = F.lit(1.0)
    for n in names:
        product = product * F.col(f"m_{n}") / F.col("t")
    return Cells(out.crossJoin(whole).select(*names, (product * F.col("t")).alias("v")), cells.spec)


__all__ = ["ship4", "ship5", "trade4v", "trade5v", "grid5v", "pulse4v", "vec2", "vec4", "modular4", "ranked4", "grid3", "cube4", "skew4", "text4", "margins", "fill_holes"]
