"""r-way merging of sorted runs inside a lane, plain and LCP-aware, with a count of the characters looked at.

The production path sorts an arrived lane again (presorted blocks make that cheap, and it spills); these kernels are for
the measure of the merging work itself.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from itertools import pairwise

import pyarrow as pa
from pyspark.sql import DataFrame


def _compare(a: str, b: str, skip: int) -> tuple[int, int]:
    """Common prefix from ``skip`` on, and characters looked at."""
    n = min(len(a), len(b))
    i = skip
    while i < n and a[i] == b[i]:
        i += 1
    return i, i - skip + 1


class LoserTree:
    """Tournament over sorted runs of (s, src_id, pos): inner nodes keep the loser of their game and its LCP.

    The LCP of a waiting head is the one with the row put out last, so a game is decided by the longer LCP, and
    characters are compared only between heads with equal ones, and only beyond it. A row costs one game per tree level.
    """

    def __init__(self, runs: list[list[tuple]]):
        self.runs = runs
        self.shared = [run_lcps(r) for r in runs]
        self.at = [0] * len(runs)
        self.leaves = 1 << max(0, len(runs) - 1).bit_length()
        self.lost: list[tuple[int, int]] = [(-1, 0)] * self.leaves
        self.looked = 0
        self.best = self._play(1)

    def _play(self, node: int) -> tuple[int, int]:
        """(run, LCP) that wins the subtree; a run number beyond the last, or -1, stands for one that is used up."""
        if node >= self.leaves:
            run = node - self.leaves
            return (run if run < len(self.runs) and self.runs[run] else -1), 0
        win, self.lost[node] = self._game(self._play(2 * node), self._play(2 * node + 1))
        return win

    def _game(self, x: tuple[int, int], y: tuple[int, int]) -> tuple[tuple[int, int], tuple[int, int]]:
        """Winner, and loser with its LCP with the winner."""
        if x[0] < 0 or y[0] < 0:
            return (y, x) if x[0] < 0 else (x, y)
        if x[1] != y[1]:
            return (x, y) if x[1] > y[1] else (y, x)
        a, b = self.runs[x[0]][self.at[x[0]]], self.runs[y[0]][self.at[y[0]]]
        h, seen = _compare(a[0], b[0], x[1])
        self.looked += seen
        if (a[0][h : h + 1], *a[1:]) <= (b[0][h : h + 1], *b[1:]):
            return x, (y[0], h)
        return y, (x[0], h)

    def __iter__(self) -> Iterator[tuple[tuple, int]]:
        while self.best[0] >= 0:
            run, h = self.best
            yield self.runs[run][self.at[run]], h
            self.at[run] += 1
            rest = self.at[run] < len(self.runs[run])
            now = (run, self.shared[run][self.at[run]]) if rest else (-1, 0)
            node = (run + self.leaves) // 2
            while node:
                now, self.lost[node] = self._game(now, self.lost[node])
                node //= 2
            self.best = now


def run_lcps(run: list[tuple]) -> list[int]:
    """LCP of every row of a sorted run with the row before it, 0 for the first."""
    return [0] + [_compare(a[0], b[0], 0)[0] for a, b in pairwise(run)]


def merge_with_lcp(runs: list[list[tuple]]) -> tuple[list[tuple], list[int], int]:
    """Merge runs of (s, src_id, pos): rows, LCP with the row before, characters looked at (those of the runs' own LCPs,
    which a sorter hands over with its run, are not counted)."""
    tree = LoserTree([r for r in runs if r])
    rows = list(tree)
    return [r for r, _ in rows], [h for _, h in rows], tree.looked


def merge_plain(runs: list[list[tuple]]) -> tuple[list[tuple], int]:
    """The same without LCPs; every comparison starts at the first character."""
    looked = 0

    class Key:
        __slots__ = ("row",)

        def __init__(self, row):
            self.row = row

        def __lt__(self, other):
            nonlocal looked
            looked += _compare(self.row[0], other.row[0], 0)[1]
            return self.row < other.row

    return [x.row for x in heapq.merge(*([Key(r) for r in run] for run in runs))], looked


def merge_lanes(moved: DataFrame, with_lcp: bool = True) -> DataFrame:
    """lane, lpos, src_id, pos, h, looked: kernel over (lane, run, src_id, pos, s); a lane is bounded by the plan."""

    def kernel(t: pa.Table) -> pa.Table:
        runs: dict[int, list[tuple]] = {}
        for run, src, pos, s in zip(*(t.column(c).to_pylist() for c in ("run", "src_id", "pos", "s")), strict=True):
            runs.setdefault(run, []).append((s, src, pos))
        parts = [sorted(r) for _, r in sorted(runs.items())]
        if with_lcp:
            rows, h, looked = merge_with_lcp(parts)
        else:
            (rows, looked), h = merge_plain(parts), None
        n = len(rows)
        return pa.table({"lane": pa.array([t.column("lane")[0].as_py()] * n, pa.int32()), "lpos": pa.array(range(1, n + 1), pa.int64()), "src_id": pa.array([r[1] for r in rows], pa.int64()), "pos": pa.array([r[2] for r in rows], pa.int32()), "h": pa.array(h if h else [None] * n, pa.int32()), "looked": pa.array([looked] * n, pa.int64())})

    return moved.groupBy("lane").applyInArrow(kernel, "lane int, lpos bigint, src_id bigint, pos int, h int, looked bigint")
