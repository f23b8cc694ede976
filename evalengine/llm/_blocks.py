"""Exact links inside groups of items that meet block against block."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evalengine.llm._arrow import trimmed

#: From the payloads of a group to the square matrix of its links.
Linker = Callable[[list[bytes]], np.ndarray]


def forest(edges: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """A spanning forest of the edges: (id, root) for every id that is not its own root."""
    above: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (up := above.get(top, top)) != top:
            top = up
        while x != top:
            above[x], x = top, above.get(x, x)
        return top

    for a, b in edges:
        x, y = root(a), root(b)
        above[max(x, y)] = min(x, y)
    return [(x, top) for x in list(above) if (top := root(x)) != x]


def block_of(id_col: str, blocks: Column) -> Column:
    return F.pmod(F.xxhash64(id_col), blocks).cast("int")


def met(items: DataFrame) -> DataFrame:
    """Copy each item (``component``, ``block`` of ``blocks``) to every pair of blocks it belongs to, and sort the pairs together."""
    pairs = items.withColumn("x", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumns({"i": F.least("block", "x"), "j": F.greatest("block", "x")})
    return pairs.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j", "id")


def verified(items: DataFrame, linker: Linker, payload: str) -> DataFrame:
    """A row for each item and pair of blocks: the number of items it links with there, their copies, and the smallest
    item of its linked part (``root``). Pairs themselves are never written out."""

    def links(rows: list[list], i: int, j: int) -> list[tuple[int, int, int, int]]:
        ids, blocks = [r[0] for r in rows], np.array([r[1] for r in rows])
        linked = linker([r[3] for r in rows])
        np.fill_diagonal(linked, False)
        if i != j:
            linked &= blocks[:, None] != blocks[None, :]
        copies = np.array([r[2] for r in rows], np.int64)
        root = np.arange(len(rows))
        while True:
            best = np.where(linked, root[None, :], len(rows)).min(axis=1, initial=len(rows))
            new = np.minimum(root, best)
            new = new[new]
            if (new == root).all():
                break
            root = new
        return [(ids[k], int(linked[k].sum()), int(copies[linked[k]].sum()), ids[root[k]]) for k in range(len(rows))]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = None, []

        def flush() -> Iterator[pa.RecordBatch]:
            if len(rows) > 1:
                out = links(rows, held[1], held[2])
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], names=["id", "items", "copies", "root"])

        for batch in batches:
            for component, i, j, *row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if (component, i, j) != held:
                    yield from flush()
                    held, rows = (component, i, j), []
                rows.append(row)
        if held is not None:
            yield from flush()

    return items.select("component", "i", "j", "id", "block", "copies", payload).mapInArrow(trimmed(run), "id long, items long, copies long, root long")
