"""Kernels over a table of strings ``(sid, body)``: one pass, no shuffle, results streamed out in bounded batches."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from phraseloom.functions.kernels import parse_many

ROWS_OUT = 20_000
#: Symbols that are parsed together; the arrays of a group stay near the processor's cache.
SYMBOLS = 1 << 16


def strings(table: DataFrame, key: str, body: str) -> DataFrame:
    """``(sid, body)`` of the rows whose body is not null."""
    return table.select(F.col(key).cast("long").alias("sid"), F.col(body).cast("string").alias("body")).where("body is not null")


def spread(rows: DataFrame, key: str = "sid") -> DataFrame:
    """Deal rows to all cores when their scan has fewer partitions (one small file); large scans stay as they are."""
    cores = rows.sparkSession.sparkContext.defaultParallelism
    return rows.repartition(4 * cores, key) if rows.rdd.getNumPartitions() < cores else rows


def flat_map(rows: DataFrame, kernel: Callable[..., Iterable[tuple]], schema: str) -> DataFrame:
    """Apply ``kernel`` to the columns of each row; its tuples become rows of ``schema``."""
    kind = T._parse_datatype_string(schema)
    arrow = to_arrow_schema(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                out.extend(kernel(*row))
                if len(out) >= ROWS_OUT:
                    yield _batch(out, arrow)
                    out = []
        if out:
            yield _batch(out, arrow)

    return rows.mapInArrow(run, kind)


def flat_map_groups(rows: DataFrame, kernel: Callable[[list[tuple]], Iterable[tuple]], schema: str) -> DataFrame:
    """``kernel`` on groups of rows, the second column a string: ``SYMBOLS`` symbols a group; a longer string is a group of its own."""
    kind = T._parse_datatype_string(schema)
    arrow = to_arrow_schema(kind)

    def groups(batches: Iterator[pa.RecordBatch]) -> Iterator[list[tuple]]:
        held, size = [], 0
        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and size + len(row[1]) > SYMBOLS:
                    yield held
                    held, size = [], 0
                held.append(row)
                size += len(row[1]) + 1
        if held:
            yield held

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for held in groups(batches):
            for row in kernel(held):
                out.append(row)
                if len(out) >= ROWS_OUT:
                    yield _batch(out, arrow)
                    out = []
        if out:
            yield _batch(out, arrow)

    return rows.mapInArrow(run, kind)


def flat_map_parsed(rows: DataFrame, kernel: Callable[[int, str, list[tuple]], Iterable[tuple]], schema: str) -> DataFrame:
    """``kernel`` on the id, the string, and its greedy parse ``(lo, hi, length, source)``, for rows ``(sid, body)``; one suffix order a group."""

    def parsed(held: list[tuple]) -> Iterator[tuple]:
        for (sid, body), phrases in zip(held, parse_many([body for _, body in held]), strict=True):
            yield from kernel(sid, body, phrases)

    return flat_map_groups(rows.select("sid", "body"), parsed, schema)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.record_batch([pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)
