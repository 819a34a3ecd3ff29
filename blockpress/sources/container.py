"""Compressed tables on disk: the segments, the codebook, and a mark that is written last and makes them count."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpress.operators.codec import Container, decompress
from blockpress.plans.encode import Codebook, code_of


def write_container(box: Container, path: str, book: Codebook | None = None) -> None:
    """Segments sorted by labels, so that readers of some labels skip the other files' row groups; then the codebook."""
    box.segments.repartitionByRange("segment", "u", "v").sortWithinPartitions("segment", "u", "v", "chunk_id").write.mode("overwrite").parquet(f"{path}/segments")
    spark = box.segments.sparkSession
    if book is not None:
        book.frame(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/codebook")
    spark.createDataFrame([(j, int(k)) for j, k in enumerate(box.cards)], "col_id int, card int").coalesce(1).write.mode("overwrite").parquet(f"{path}/alphabets")


def read_container(spark: SparkSession, path: str) -> Container:
    cards = [r.card for r in spark.read.parquet(f"{path}/alphabets").orderBy("col_id").collect()]
    return Container(spark.read.parquet(f"{path}/segments"), cards)


def read_columns(spark: SparkSession, path: str, columns: list[int]) -> DataFrame:
    """Only these columns' codes; blocks of other column labels are skipped."""
    return decompress(read_container(spark, path), only=columns)


def labels_with_code(box: Container, column: int, codes: list[int]) -> list[int]:
    """Row labels whose block of this column can hold one of the codes at all, by the stored counts; all of them where no counts are."""
    v = int(box.columns[column])
    if not box.freq:
        return list(range(box.k_r))
    return sorted(u for (u, w), (f, _) in box.freq.items() if w == v and any(c < len(f) and f[c] > 0 for c in codes))


def rows_with_code(box: Container, column: int, code: int | list[int]) -> DataFrame:
    """``row_id`` of rows with a code (or one of several) in a column: decodes that column's blocks under the labels that can hold it."""
    codes = [code] if isinstance(code, int) else list(code)
    found = decompress(box, only=[column], only_u=labels_with_code(box, column, codes))
    return found.where(F.element_at("codes", 1).isin(codes)).select("row_id")


def codes_where(spark: SparkSession, book: Codebook, column: str, predicate: str) -> list[int]:
    """Codes of a dictionary column whose values satisfy a SQL predicate on its name: equality, range, IN, LIKE, IS NULL."""
    c = next(x for x in book.columns if x.name == column)
    if c.kind != "C":
        raise ValueError(f"{column} holds quantile codes, which have no values")
    values = spark.createDataFrame([(v,) for v in c.values] + ([(None,)] if c.has_null else []), _schema_of(c))
    return sorted(r[0] for r in values.where(predicate).select(code_of(values, c)).collect())  # an alphabet's size


def _schema_of(c) -> str:
    from pyspark.sql.types import _infer_type

    return f"`{c.name}` {_infer_type(c.values[0]).simpleString()}"


def rows_where(box: Container, book: Codebook, column: str, predicate: str) -> DataFrame:
    """``row_id`` of rows whose value in a dictionary column satisfies a SQL predicate, found on the compressed table."""
    j = [c.name for c in book.columns].index(column)
    return rows_with_code(box, j, codes_where(box.segments.sparkSession, book, column, predicate))
