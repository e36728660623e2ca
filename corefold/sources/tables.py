"""Tables into cells."""

from __future__ import annotations

from math import prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from corefold.functions.tensor import Cells, TensorSpec, index_columns

#: Most cells of a grid that is spelled out to fill holes; larger arrays are filled within chunks.
GRID_LIMIT = 20_000_000
#: Most labels of a mode.
LABEL_LIMIT = 100_000


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def dictionary(df: DataFrame, column: str) -> list:
    """Sorted distinct labels of a mode; from a dimension table, so that sizes do not depend on the facts."""
    found = [r[0] for r in df.select(column).filter(F.col(column).isNotNull()).distinct().orderBy(column).limit(LABEL_LIMIT + 1).collect()]
    if len(found) > LABEL_LIMIT:
        raise ValueError(f"{column} has over {LABEL_LIMIT} labels: too many for a mode")
    return found


def label_index(column: Column | str, labels: list) -> Column:
    """Place of a label in its dictionary, from 0; null for others."""
    column = F.col(column) if isinstance(column, str) else column
    pairs = [x for i, label in enumerate(labels) for x in (F.lit(label), F.lit(i))]
    return F.try_element_at(F.create_map(*pairs), column).cast("int")


def cells_from_table(df: DataFrame, modes: dict[str, tuple[Column, int]], value: Column, fill: float | int | None = 0, on_missing: str = "reject") -> Cells:
    """Cross-tabulate: modes name -> (index column, size); value is an aggregate.

    on_missing: rows whose index is null or outside its mode, or whose value is null or
    not a number, raise ('reject') or are left out ('drop'). fill: value of cells without
    rows, None to leave them out.
    """
    names = index_columns(len(modes))
    spec = TensorSpec(tuple(size for _, size in modes.values()))
    keyed = df.select(*df.columns, *[c.cast("int").alias(n) for n, (c, _) in zip(names, modes.values(), strict=True)])
    inside = None
    for n, size in zip(names, spec.dims, strict=True):
        ok = F.coalesce(F.col(n).between(0, size - 1), F.lit(False))
        inside = ok if inside is None else inside & ok
    if on_missing == "drop":
        keyed = keyed.filter(inside)
    else:
        keyed = keyed.withColumn(names[0], F.when(inside, F.col(names[0])).otherwise(F.raise_error(F.lit("a row has no place in the array")).cast("int")))
    cells = keyed.groupBy(*names).agg(value.alias("v"))
    if fill is None:
        return Cells(cells, spec)
    return Cells(fill_holes(Cells(cells, spec), fill).df, spec)


def index_grid(spark: SparkSession, spec: TensorSpec) -> DataFrame:
    """Every index of a small array."""
    if spec.size > GRID_LIMIT:
        raise ValueError(f"{spec.size} cells are too many to spell out: fill within chunks")
    running, columns = 1, []
    for name, d in zip(index_columns(spec.order), spec.dims, strict=True):
        columns.append(F.pmod(F.floor(F.col("id") / running), F.lit(d)).cast("int").alias(name))
        running *= d
    return spark.range(prod(spec.dims)).select(*columns)


def fill_holes(cells: Cells, fill: float | int = 0) -> Cells:
    names = index_columns(cells.spec.order)
    grid = index_grid(cells.df.sparkSession, cells.spec)
    kind = cells.df.schema["v"].dataType
    return Cells(grid.join(cells.df, names, "left").select(*names, F.coalesce("v", F.lit(fill).cast(kind)).alias("v")), cells.spec)


def fill_ratio(cells: Cells) -> float:
    return cells.df.count() / cells.spec.size


def require_dense(cells: Cells, least: float = 0.01) -> Cells:
    """The methods are for dense arrays: an array that is nearly all holes is refused."""
    if (ratio := fill_ratio(cells)) < least:
        raise ValueError(f"only {ratio:.2%} of the cells have rows")
    return cells


def unpivot_measures(df: DataFrame, ids: list[str], measures: list[str]) -> DataFrame:
    """A row for each measure: var (its place in the list) and val."""
    casted = df.select(*ids, *[F.col(m).cast("double").alias(m) for m in measures])
    return casted.unpivot(ids, measures, "name", "val").withColumn("var", label_index("name", measures)).drop("name")


def explode_vector(df: DataFrame, column: str, shape: tuple[int, ...] | None = None, ids: tuple[str, ...] = ()) -> DataFrame:
    """An array column as cells: its position becomes one index (pos), or several (p_1 .. of `shape`, first fastest)."""
    out = df.select(*ids, F.posexplode(column).alias("pos", "val"))
    if shape:
        running = 1
        for k, d in enumerate(shape):
            out = out.withColumn(f"p_{k + 1}", F.pmod(F.floor(F.col("pos") / running), F.lit(d)).cast("int"))
            running *= d
        out = out.drop("pos")
    return out


def cell_schema(n: int) -> T.StructType:
    return T.StructType([*(T.StructField(c, T.IntegerType()) for c in index_columns(n)), T.StructField("v", T.DoubleType())])


def read_cells(spark: SparkSession, path: str, fmt: str, spec: TensorSpec, **options: str) -> Cells:
    """Cells from csv, json, orc or parquet under an explicit schema."""
    return Cells(spark.read.format(fmt).schema(cell_schema(spec.order)).options(**options).load(path), spec)


def save_frame(df: DataFrame, path: str, mode: str = "error") -> None:
    df.write.mode(mode).parquet(path)
