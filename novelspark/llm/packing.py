"""Sum-of-squares online packing (operator 6).

Documents arrive one by one. A document of more than a window is cut into whole windows and a rest. Each rest goes to the fill
level that keeps the sum of the squared counts of partly filled windows smallest; a level array holds these counts, so a
placement looks at one number a level and never at the windows themselves. Every task packs its own documents: no shuffle.

When a task ends, or holds ``MAX_OPEN`` open windows, open windows are settled: of windows that hold t tokens together the
ceil(t / size) fullest stay as they were placed, and only the pieces of the emptiest are cut to fill the gaps of the others. So a task
leaves less than one window of padding and holds at most ``MAX_OPEN`` windows of ids, also if no rests ever add up to a window.

Defined cases: a null or empty text is its end token alone; repeated rows are packed each; an empty table gives no rows.
Which rows meet in one window follows from the input splits; a lost task packs the same split again to the same windows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import documents, slices

WINDOW = 1024
END_ID = 0
#: Window numbers of a task start at its number times this.
TASK_STRIDE = 1 << 40
#: Open windows of a task beyond which they are settled.
MAX_OPEN = 4096
COLUMNS = ["key", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]


class SumOfSquares:
    """Fill levels 1 .. size-1 with the number of partly filled windows at each, and the open windows themselves."""

    def __init__(self, size: int = WINDOW):
        self.size, self.used = size, 0
        self.counts = np.zeros(size + 1, dtype=np.int64)
        self.open: list[list[int]] = [[] for _ in range(size + 1)]

    def new_window(self) -> int:
        self.used += 1
        return self.used - 1

    def clear(self) -> None:
        """Forgets all open windows."""
        self.counts[:] = 0
        self.open = [[] for _ in range(self.size + 1)]

    def reopen(self, window: int, level: int) -> None:
        self.open[level].append(window)
        self.counts[level] += 1

    def place(self, length: int) -> tuple[int, int]:
        """Window and offset for a piece shorter than a window."""
        counts, size = self.counts, self.size
        levels = np.arange(0, size - length + 1)
        # change of the sum of squares when a window goes from a level to that level plus the length
        leaving = np.where(levels > 0, 1 - 2 * counts[levels], 0)
        reached = levels + length
        arriving = np.where(reached < size, 2 * counts[reached] + 1, 0)
        change = np.where((levels == 0) | (counts[levels] > 0), leaving + arriving, np.iinfo(np.int64).max)
        best = int(len(levels) - 1 - np.argmin(change[::-1]))  # among equals the fullest
        if best:
            window = self.open[best].pop()
            counts[best] -= 1
        else:
            window = self.new_window()
        if best + length < size:
            self.open[best + length].append(window)
            counts[best + length] += 1
        return window, best


class Packer:
    """Pieces (name, start, ids, document's tokens) of windows; finished windows come out as rows of COLUMNS."""

    def __init__(self, size: int = WINDOW, max_open: int = MAX_OPEN):
        self.size, self.max_open, self.levels = size, max_open, SumOfSquares(size)
        self.waiting: dict[int, list[tuple]] = {}
        self.placed = self.recut = 0

    def _rows(self, window: int, pieces: list[tuple]) -> list[tuple]:
        out, at = [], 0
        for name, start, ids, total in pieces:
            out.append((name, start, len(ids), zlib.crc32(np.ascontiguousarray(ids, dtype="<u4").tobytes()), total, window, at))
            at += len(ids)
        return out

    def add(self, name, ids: np.ndarray) -> list[tuple]:
        """Takes a document; gives the rows of windows that it fills."""
        out, whole = [], len(ids) // self.size * self.size
        for start in range(0, whole, self.size):
            out += self._rows(self.levels.new_window(), [(name, start, ids[start : start + self.size], len(ids))])
        if rest := len(ids) - whole:
            window, offset = self.levels.place(rest)
            self.placed += rest
            self.waiting.setdefault(window, []).append((name, whole, ids[whole:], len(ids)))
            if offset + rest == self.size:
                out += self._rows(window, self.waiting.pop(window))
            elif len(self.waiting) > self.max_open:
                out += self.settle()
        return out

    def settle(self, last: bool = False) -> list[tuple]:
        """Fills the fullest open windows with the pieces of the emptiest; what is still open stays so, or comes out if this is the ``last`` call."""
        fill = lambda pieces: sum(len(p[2]) for p in pieces)
        order = sorted(self.waiting.items(), key=lambda w: (-fill(w[1]), w[0]))
        kept = -(-sum(fill(pieces) for _, pieces in order) // self.size)
        loose = [p for _, pieces in order[kept:] for p in pieces][::-1]
        self.recut += fill(loose)
        out, self.waiting = [], {}
        self.levels.clear()
        for window, pieces in order[:kept]:
            free = self.size - fill(pieces)
            while free and loose:
                name, start, ids, total = loose.pop()
                pieces.append((name, start, ids[:free], total))
                if len(ids) > free:
                    loose.append((name, start + free, ids[free:], total))
                free -= min(free, len(ids))
            if last or not free:
                out += self._rows(window, pieces)
            else:
                self.waiting[window] = pieces
                self.levels.reopen(window, self.size - free)
        return out


def pack(docs: DataFrame, key: str = "doc_id", text: str = "text", window: int = WINDOW, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    """One row a piece: key, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        from .bpe import encoder

        first = TaskContext.get().partitionId() * TASK_STRIDE
        packer, key_type = Packer(window), None

        def frame(rows: list[tuple]) -> pa.RecordBatch:
            names, *numbers = zip(*rows, strict=True)
            numbers[4] = [first + x for x in numbers[4]]
            return pa.RecordBatch.from_arrays([pa.array(names, type=key_type), *(pa.array(x, type=pa.int64()) for x in numbers)], names=COLUMNS)

        for batch in slices(batches):
            rows: list[tuple] = []
            key_type = batch.column(0).type
            for name, ids in zip(batch.column(0).to_pylist(), encoder(path).encode(batch.column(1).to_pylist()), strict=True):
                rows += packer.add(name, np.append(ids, np.uint32(end_id)))
            if rows:
                yield frame(rows)
        if rows := packer.settle(last=True):
            yield frame(rows)

    rows = docs.select(F.col(key).alias("key"), F.col(text).alias("text"))
    schema = f"key {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
    return rows.mapInArrow(run, schema).withColumnRenamed("key", key)


def op6_sum_of_squares(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(documents(spark, sf_dir))
