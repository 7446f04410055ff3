"""Longest earlier copies from intervals of common prefixes.

Classes of equal suffixes stand in their order, each with what it has in common with the one before it and the
place where it stands first. An interval of depth d is a run of classes whose neighbours have d lines or more in
common; all its members but the first in place are later copies of d lines. For a class that is
the deepest interval in which another member stands earlier: it ends at the nearest class before or behind it with an
earlier place. One pass over each range of classes with a stack finds it inside the range. Intervals that
reach over the border of ranges are told by stairs, the earliest place for each depth at the border, which are as long
as the prefix that the classes at the border have in common.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farpoint.llm.common import Staging

Place = tuple[int, int, int, int]
Stairs = list[tuple[int, Place]]
#: Behind no border: deeper than any prefix.
OPEN = 1 << 30


class Scan:
    """One pass over (rank, place, common, least) in order. Rows come out as [rank, place, copied, before, behind] as soon as a border of intervals is passed.

    ``copied`` is the depth found inside the range, ``before`` and ``behind`` what the class has in common with all up to the
    range's border where an earlier place may stand beyond it, 0 where it cannot. Depths under ``least`` do not count.
    """

    def __init__(self):
        self.rows: list[list] = []
        self.stack: list[tuple[Place, int, int]] = []  # place, common with the one below, index
        self.opening: Stairs = []
        self.closing: Stairs = []
        self.through = OPEN

    def add(self, rank: int, place: Place, common: int, least: int) -> list[list]:
        """Takes a class; returns rows that are done."""
        done: list[list] = []
        depth = common if common >= least else 0
        self.through = min(self.through, depth)
        if not depth:
            done, self.rows = self.rows, []
            self.stack.clear()
        me, stack = [rank, place, 0, 0, 0], self.stack
        while stack and stack[-1][0] > place:
            _, below, at = stack.pop()
            self.rows[at][2] = max(self.rows[at][2], depth)
            depth = min(depth, below)
        if stack:
            me[2] = depth
        elif self.through:
            me[3] = depth
            if self.opening and self.opening[-1][0] == depth:
                self.opening.pop()  # an earlier place at the same depth
            self.opening.append((depth, place))
        stack.append((place, depth, len(self.rows)))
        self.rows.append(me)
        return done

    def end(self) -> list[list]:
        """The last rows; then ``closing`` is known."""
        depth = OPEN
        for place, below, at in reversed(self.stack):
            self.rows[at][4] = depth
            if self.closing and self.closing[-1][0] == depth:
                self.closing.pop()
            self.closing.append((depth, place))
            depth = min(depth, below)
        return self.rows


def cut_down(stairs: Stairs, through: int, more: Stairs) -> Stairs:
    """``more`` at a border, and behind it the stairs of the border before, of which only ``through`` lines reach here."""
    out = list(more)
    for depth, place in stairs if through else []:
        depth = min(depth, through, out[-1][0] if out else OPEN)
        if out and out[-1][1] <= place:
            continue
        if out and out[-1][0] == depth:
            out[-1] = (depth, place)
        else:
            out.append((depth, place))
    return out


def _scan_ranges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(rank, known, doc_id, row_no, pos, common, span) sorted by rank -> RANGES: classes, and steps of the stairs with their side."""
    part, held, pass_over, told = TaskContext.get().partitionId(), Scan(), False, []
    names = ["rank", "copied", "before", "behind", "side", "depth", "known", "doc_id", "row_no", "pos", "part"]
    kinds = [pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32()]

    def made(rows):
        columns = list(zip(*rows, strict=True)) or [[]] * len(names)
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)

    def row(rank, place, *depths):
        return (rank, *depths, None, None, *place, part)

    for batch in batches:
        for rank, known, doc, row_no, pos, common, least in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            pass_over = True
            told += [row(*r) for r in held.add(rank, (known, doc, row_no, pos), common, least)]
            if len(told) >= 20_000:
                yield made(told)
                told = []
    told += [row(*r) for r in held.end()]
    steps = [("opening", *x) for x in held.opening] + [("closing", *x) for x in held.closing] + [("through", held.through, (0, 0, 0, 0))] * pass_over
    told += [(None, None, None, None, side, depth, *place, part) for side, depth, place in steps]
    for lo in range(0, len(told), 20_000):
        yield made(told[lo : lo + 20_000])


RANGES = "rank long, copied int, before int, behind int, side string, depth int, known int, doc_id long, row_no long, pos int, part int"


def earlier_place(stairs: Stairs, place: Place) -> int:
    """The greatest depth at which an earlier place than ``place`` stands."""
    return next((depth for depth, other in stairs if other < place), 0)


def _finished(borders: dict[int, tuple[Stairs, Stairs]]):
    """(rank, copied, before, behind, known, doc_id, row_no, pos, part) -> (rank, copied) with what stands beyond the borders."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ranks, depths = [], []
            for rank, copied, before, behind, known, doc, row, pos, part in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                left, right = borders.get(part, ([], []))
                place = (known, doc, row, pos)
                if before:
                    copied = max(copied, min(before, earlier_place(left, place)))
                if behind:
                    copied = max(copied, min(behind, earlier_place(right, place)))
                ranks.append(rank)
                depths.append(copied)
            yield pa.RecordBatch.from_arrays([pa.array(ranks, pa.int64()), pa.array(depths, pa.int32())], names=["rank", "copied"])

    return run


def longest_copies(stage: Staging, classes: DataFrame) -> DataFrame:
    """(rank, doc_id, row_no, pos, common, span) -> (rank, copied): how many lines of the class's first suffix an earlier place holds.

    Copies of fewer than ``span`` lines do not count; span is told by these lines, so classes that have them in common
    have it as well. Places are in the order of doc_id (null first), row_no, pos.
    """
    rows = classes.select("rank", F.col("doc_id").isNotNull().cast("int").alias("known"), F.coalesce("doc_id", F.lit(0)).alias("doc_id"), "row_no", "pos", F.col("common").cast("int").alias("common"), "span")
    made = stage.keep(rows.repartitionByRange("rank").sortWithinPartitions("rank").mapInArrow(_scan_ranges, RANGES), "ranges")
    found, stairs = made.where("side IS NULL"), made.where("side IS NOT NULL")
    told: dict[int, dict[str, Stairs]] = {}
    for r in stairs.orderBy("part", "side", F.desc("depth")).collect():  # for each range at most twice the prefix at its border
        told.setdefault(r.part, {"opening": [], "closing": [], "through": []})[r.side].append((r.depth, (r.known, r.doc_id, r.row_no, r.pos)))
    borders: dict[int, tuple[Stairs, Stairs]] = {}
    order = sorted(told)
    left: Stairs = []
    for part in order:
        borders[part] = (left, [])
        left = cut_down(left, told[part]["through"][0][0], told[part]["closing"])
    right: Stairs = []
    for part in reversed(order):
        borders[part] = (borders[part][0], right)
        right = cut_down(right, told[part]["through"][0][0], told[part]["opening"])
    return found.select("rank", "copied", "before", "behind", "known", "doc_id", "row_no", "pos", "part").mapInArrow(_finished(borders), "rank long, copied int")
