"""Stage 2: partitions ordered by their distance to the parent centre, packed into leaves, dealt to worker slots."""
from __future__ import annotations

from bisect import bisect_left, bisect_right, insort

from pyspark.sql import DataFrame, Window, functions as F


def default_leaf_capacity(n_p: int, n_w: int, fanout: int) -> int:
    """Several leaves a slot, or dealing would do nothing."""
    return max(1, min(fanout, n_p // (4 * n_w)))


def pack(parts: DataFrame, leaf_capacity: int, balance: str = "objects") -> DataFrame:
    """[pid, dist_to_parent, n_objects, bucket]: walk the partitions by key and fill leaves evenly.

    "partitions": equal numbers of partitions a leaf. "objects": as many leaves, cut at equal shares of the objects.
    The window has one row a partition, so a single task is right here.
    """
    parts = parts.select("pid", "dist_to_parent", "n_objects")
    w = Window.orderBy("dist_to_parent", "pid")
    n_leaves = F.ceil(F.count("*").over(Window.partitionBy()) / F.lit(leaf_capacity))
    if balance == "partitions":
        rank = F.row_number().over(w) - 1
        bucket = F.floor(rank * n_leaves / F.count("*").over(Window.partitionBy()))
    else:
        total = F.sum("n_objects").over(Window.partitionBy())
        before = F.sum("n_objects").over(w) - F.col("n_objects") / 2
        bucket = F.least(F.floor(before * n_leaves / total), n_leaves - 1)
    return parts.withColumn("bucket", bucket.cast("int"))


def deal(packed: DataFrame, n_w: int) -> DataFrame:
    """Leaves to slots in turn, so that neighbours in key order part."""
    return packed.withColumn("slot", F.pmod("bucket", F.lit(n_w)).cast("int"))


def locate(cand: DataFrame, placement: DataFrame) -> DataFrame:
    """bucket and slot of every candidate partition; the placement has one row a partition and is broadcast."""
    p = placement.select(F.col("pid").alias("p_"), "bucket", "slot")
    return cand.join(F.broadcast(p), F.col("pid") == F.col("p_")).drop("p_")


class OrderedLeafIndex:
    """An ordered map key -> partitions with linked leaves of bounded fanout (a B+-tree's lookups, ranges and edits)."""

    def __init__(self, entries: list[tuple[float, int]], fanout: int = 20):
        self.fanout, self.comparisons = fanout, 0
        items = sorted(entries)
        self.leaves = [items[i : i + fanout] for i in range(0, len(items), fanout)] or [[]]
        self.key_of = {pid: key for key, pid in items}

    def _leaf(self, entry: tuple[float, int]) -> int:
        lo, hi = 0, len(self.leaves) - 1
        while lo < hi:
            mid = (lo + hi) // 2
            self.comparisons += 1
            if self.leaves[mid] and self.leaves[mid][-1] >= entry:
                hi = mid
            else:
                lo = mid + 1
        return lo

    def lookup(self, pid: int) -> int | None:
        """Number of the leaf that holds `pid`."""
        if pid not in self.key_of:
            return None
        entry = (self.key_of[pid], pid)
        leaf = self._leaf(entry)
        self.comparisons += max(1, len(self.leaves[leaf]).bit_length())
        k = bisect_left(self.leaves[leaf], entry)
        return leaf if k < len(self.leaves[leaf]) and self.leaves[leaf][k] == entry else None

    def lookup_linear(self, pid: int) -> int | None:
        """The same by reading all entries in turn."""
        for number, leaf in enumerate(self.leaves):
            for _, p in leaf:
                self.comparisons += 1
                if p == pid:
                    return number
        return None

    def range(self, low: float, high: float) -> list[int]:
        out, at = [], self._leaf((low, -1))
        while at < len(self.leaves):
            leaf = self.leaves[at]
            a, b = bisect_left(leaf, (low, -1)), bisect_right(leaf, (high, float("inf")))
            out += [p for _, p in leaf[a:b]]
            if b < len(leaf):
                break
            at += 1
        return out

    def insert(self, key: float, pid: int) -> None:
        leaf = self._leaf((key, pid))
        insort(self.leaves[leaf], (key, pid))
        self.key_of[pid] = key
        if len(self.leaves[leaf]) > self.fanout:
            half = len(self.leaves[leaf]) // 2
            self.leaves[leaf : leaf + 1] = [self.leaves[leaf][:half], self.leaves[leaf][half:]]

    def remove(self, pid: int) -> None:
        key = self.key_of.pop(pid)
        leaf = self._leaf((key, pid))
        self.leaves[leaf].remove((key, pid))
        if not self.leaves[leaf] and len(self.leaves) > 1:
            del self.leaves[leaf]

    def entries(self) -> list[tuple[float, int]]:
        return [e for leaf in self.leaves for e in leaf]
