"""A data source of the changes that make near duplicates of documents, made where they are read."""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Slice(InputPartition):
    def __init__(self, runs: np.ndarray):
        self.runs = runs


class SyntheticChanges(DataSource):
    """format('synthetic_changes'): options runs, as id_runs() makes them, or low and high, and partitions; for each doc_id in the runs the word that its near duplicate has in place of one."""

    @classmethod
    def name(cls) -> str:
        return "synthetic_changes"

    def schema(self) -> str:
        return "doc_id bigint, word string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(low, high) of the runs of consecutive numbers among sorted ids; a run may go on in the next row."""
    for b in batches:
        ids = np.unique(b.column(0).drop_null().to_numpy())
        if len(ids):
            cut = np.flatnonzero(ids[1:] != ids[:-1] + 1)
            yield pa.RecordBatch.from_arrays([pa.array(ids[np.append(0, cut + 1)]), pa.array(ids[np.append(cut, len(ids) - 1)])], ["low", "high"])


def id_runs(docs: DataFrame) -> str:
    """The doc_ids of docs as runs of consecutive numbers, for the option runs: ids with gaps make no row for what lies in a gap."""
    found = docs.select("doc_id").repartitionByRange("doc_id").sortWithinPartitions("doc_id").mapInArrow(_runs, "low bigint, high bigint").toArrow()
    return base64.b64encode(_joined(np.column_stack([found.column(k).to_numpy() for k in (0, 1)])).tobytes()).decode()


def _joined(runs: np.ndarray) -> np.ndarray:
    """Runs in order, with those that meet or share ids as one."""
    runs = runs[np.lexsort((runs[:, 1], runs[:, 0]))].astype(np.int64)
    if not len(runs):
        return runs
    top = np.maximum.accumulate(runs[:, 1])
    first = np.append(True, runs[1:, 0] - 1 > top[:-1])
    starts = np.flatnonzero(first)
    return np.column_stack([runs[starts, 0], top[np.append(starts[1:], len(runs)) - 1]])


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        if "runs" in options:
            self.runs = np.frombuffer(base64.b64decode(options["runs"]), np.int64).reshape(-1, 2)
        else:
            self.runs = np.array([[int(options.get("low", 0)), int(options.get("high", 999))]], np.int64)
        self.parts = int(options.get("partitions", 2))

    def partitions(self) -> list[Slice]:
        sizes = self.runs[:, 1] - self.runs[:, 0] + 1
        before, total = np.cumsum(sizes) - sizes, int(sizes.sum())
        edges = [total * k // self.parts for k in range(self.parts + 1)]
        return [Slice(self._between(before, sizes, a, b)) for a, b in zip(edges, edges[1:], strict=False)]

    def _between(self, before: np.ndarray, sizes: np.ndarray, a: int, b: int) -> np.ndarray:
        """Runs of the ids from place a to before place b."""
        lo, hi = np.maximum(before, a), np.minimum(before + sizes, b)
        held = hi > lo
        return np.column_stack([self.runs[held, 0] + (lo - before)[held], self.runs[held, 0] + (hi - before)[held] - 1])

    def read(self, partition: Slice) -> Iterator[tuple[int, str]]:
        for low, high in partition.runs.tolist():
            for i in range(low, high + 1):
                yield i, "x" + hashlib.md5(f"change:{i}".encode()).hexdigest()[:6]
