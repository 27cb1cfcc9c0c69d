"""What the operators share: column helpers, and tables in the shared scratch folder."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.scratch import Scratch


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def slices(batches, column: int = 1, size: int = 2_000_000):
    """Arrow batches in parts of at most ``size`` bytes of text (a longer text is a part of its own), so that a worker holds little."""
    import numpy as np
    import pyarrow.compute as pc

    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        ends, at = np.cumsum(sizes), 0
        while at < batch.num_rows:
            before = int(ends[at - 1]) if at else 0
            end = max(at + 1, int(np.searchsorted(ends, before + size, side="right")))
            yield batch.slice(at, end - at)
            at = end
    give_back()


def give_back() -> None:
    """Returns a worker's freed memory to the system: workers live on between tasks, beside the executor's heap."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def text_of(column="text"):
    """The text, empty where null."""
    return F.coalesce(F.col(column), F.lit(""))


def let(value, body):
    """``body`` of a value that is computed once, also inside lambdas, where a plain expression would be computed each time."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def prefix(values, zero, step, block: int = 64):
    """Array column with the fold by ``step`` (associative) of all earlier elements for each element.

    Blocks of b elements are folded first: about n * b / 2 + (n / b)**2 / 2 steps, with b growing as the cube root of n.
    """

    def inner(s, b):
        n = F.size(s)
        group = lambda i: F.floor(i / b).cast("int")
        blocks = F.when(n > 0, F.sequence(F.lit(0), group(n - 1))).otherwise(F.array().cast("array<int>"))
        folds = F.transform(blocks, lambda g: F.aggregate(F.slice(s, g * b + 1, b), zero, step))
        before = let(folds, lambda t: F.transform(t, lambda _, g: F.aggregate(F.slice(t, F.lit(1), g), zero, step)))
        return let(before, lambda e: F.transform(s, lambda _, i: F.aggregate(F.slice(s, group(i) * b + 1, i - group(i) * b), F.get(e, group(i)), step)))

    return let(values, lambda s: let(F.greatest(F.lit(block), F.ceil(F.cbrt(F.size(s) * 2.0)).cast("int")), lambda b: inner(s, b)))


def prefix_sums(sizes):
    """Array column with the sum of all earlier elements for each element."""
    return prefix(sizes, F.lit(0).cast("long"), lambda a, x: a + x)


TEXT_BLOCK = 256


def text_blocks(text):
    """The text in pieces of TEXT_BLOCK code points."""
    return F.regexp_extract_all(text, F.lit(rf"(?s).{{1,{TEXT_BLOCK}}}"), F.lit(0))


def cut(blocks, start, size):
    """``size`` code points from ``start`` of a text in blocks; it costs what is cut, not what stands before."""
    first = F.floor(start / TEXT_BLOCK).cast("int")
    number = F.floor((start + size - 1) / TEXT_BLOCK).cast("int") - first + 1
    held = F.array_join(F.slice(blocks, first + 1, number), "")
    return F.when(size > 0, F.substr(held, (start - first * TEXT_BLOCK + 1).cast("int"), size.cast("int"))).otherwise(F.lit(""))


__all__ = ["Scratch", "cut", "documents", "let", "prefix", "prefix_sums", "slices", "text_blocks", "text_of"]
