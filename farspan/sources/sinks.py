"""Writers for scores and selections."""

from __future__ import annotations

from pyspark.sql import DataFrame


def write(df: DataFrame, path: str, fmt: str = "parquet", by: str | None = None, rows_per_file: int | None = None, mode: str = "errorifexists") -> None:
    writer = df.write.format(fmt).mode(mode)
    if rows_per_file:
        writer = writer.option("maxRecordsPerFile", rows_per_file)
    (writer.partitionBy(by) if by else writer).save(path)


def write_selection(df: DataFrame, path: str, fmt: str = "parquet", rows_per_file: int = 100_000) -> None:
    """A training set, one folder per category; array columns become text in formats without arrays."""
    if fmt in ("csv", "text"):
        from pyspark.sql import functions as F

        df = df.select(*[F.concat_ws(" ", c).alias(c) if t.startswith("array") else F.col(c) for c, t in df.dtypes])
    write(df, path, fmt, "category", rows_per_file)


def save_bucketed(df: DataFrame, name: str, by: str, buckets: int) -> None:
    """A catalog table whose later joins on ``by`` need no shuffle."""
    df.write.bucketBy(buckets, by).sortBy(by).mode("overwrite").saveAsTable(name)


def write_slices(df_of_slice, slices: list[str], root: str, exists) -> list[str]:
    """Scores slice by slice: slices whose folder is complete are skipped, so that a long run can be resumed."""
    done = []
    for s in slices:
        path = f"{root}/slice={s}"
        if not exists(f"{path}/_SUCCESS"):
            df_of_slice(s).write.mode("overwrite").parquet(path)
            done.append(s)
    return done
