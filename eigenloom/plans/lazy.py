"""Lazy chains of column operations on tall blocks, and the identity of stored blocks.

Scaling, sums, views, column assignment and products with a small matrix are all linear in the columns of the stored blocks, so a chain is kept as one
small table of coefficients: output column -> {(block, column): coefficient}. However long the chain, it runs as one scan of the blocks that are still
referred to, one join on their interval, and one projection in generated code; nothing between is written. Factors are multiplied before they meet the data.
"""

from __future__ import annotations

from collections import OrderedDict
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from eigenloom.operators import dense


@dataclass(frozen=True)
class BlockId:
    """Names content, not a layout: a block and its transpose share it, so a cached or stored copy serves both."""

    content: str
    transposed: bool = False

    def t(self) -> BlockId:
        return BlockId(self.content, not self.transposed)


class RecentBlocks:
    """Keeps the newest blocks persisted within a budget of bytes; the one used longest ago leaves first."""

    def __init__(self, budget_bytes: int):
        self.budget, self.held = budget_bytes, OrderedDict()

    def put(self, name: BlockId, block: DataFrame, size: int) -> DataFrame:
        if size <= self.budget and name.content not in self.held:
            while self.held and sum(s for _, s in self.held.values()) + size > self.budget:
                self.held.popitem(last=False)[1][0].unpersist()
            self.held[name.content] = (block.persist(StorageLevel.MEMORY_AND_DISK), size)
        return block

    def get(self, name: BlockId) -> DataFrame | None:
        if name.content not in self.held:
            return None
        self.held.move_to_end(name.content)
        return self.held[name.content][0]


class Tall:
    """A tall block, stored or still to be made."""

    def __init__(self, blocks: dict[int, DataFrame], columns: list[dict[tuple[int, int], float]]):
        used = {b for c in columns for b, _ in c}
        self.blocks, self.columns = {b: f for b, f in blocks.items() if b in used}, columns

    @classmethod
    def stored(cls, block: DataFrame, width: int) -> Tall:
        return cls({id(block): block}, [{(id(block), c): 1.0} for c in range(width)])

    @property
    def width(self) -> int:
        return len(self.columns)

    def times(self, small: np.ndarray) -> Tall:
        """This block times a small matrix."""
        made = []
        for weights in np.asarray(small, float).T:
            total: dict = {}
            for w, column in zip(weights, self.columns):
                for key, v in column.items() if w else ():
                    total[key] = total.get(key, 0.0) + w * v
            made.append(total)
        return Tall(self.blocks, made)

    def scale(self, alpha: float) -> Tall:
        return self.scale_columns([alpha] * self.width)

    def scale_columns(self, factors) -> Tall:
        return self.times(np.diag(np.asarray(factors, float)))

    def view(self, columns: list[int]) -> Tall:
        return Tall(self.blocks, [self.columns[c] for c in columns])

    def set_columns(self, columns: list[int], other: Tall) -> Tall:
        made = list(self.columns)
        for at, column in zip(columns, other.columns):
            made[at] = column
        return Tall(self.blocks | other.blocks, made)

    def beside(self, other: Tall) -> Tall:
        return Tall(self.blocks | other.blocks, self.columns + other.columns)

    def __add__(self, other: Tall) -> Tall:
        if self.width != other.width:
            raise ValueError("blocks of one width are added")
        return self.beside(other).times(np.vstack([np.eye(self.width)] * 2))

    def __sub__(self, other: Tall) -> Tall:
        return self + other.scale(-1.0)

    def frame(self) -> DataFrame:
        """The chunk frame of this block, as one projection."""
        if not self.blocks:
            raise ValueError("no stored block is left in this expression, so its rows are unknown")
        names = {b: f"d{k}" for k, b in enumerate(self.blocks)}

        def column(terms):
            def cell(r):
                parts = [F.get(names[b], F.col("rows") * c + r) * F.lit(v) for (b, c), v in terms.items() if v]
                return reduce(lambda x, y: x + y, parts) if parts else F.lit(0.0)

            return F.transform(F.sequence(F.lit(0), F.col("rows") - 1), cell)

        made = dense.aligned(list(self.blocks.values())).select("iv", "rows", F.concat(*(column(c) for c in self.columns)).alias("data"))
        made.columns_held = self.width
        return made
