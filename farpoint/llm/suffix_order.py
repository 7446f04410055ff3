"""A suffix array over line-ID sequences by distributed prefix doubling, with the common prefixes of its neighbours.

Only lines that stand more than once have an ID; a line that stands once ends a sequence, as a text's end
does. Sequences hold, for each line, the rank of the class of suffixes that agree with the one from there in
the first ``width`` lines. A round takes classes apart by the ranks at the places width, 2 * width and 3 *
width further on, two doublings at once: the distinct keys are put in order over all machines,
and a key's rank is that of its class and the number of suffixes before it there. Suffixes that are alone, or whose
sequence has ended, are settled and take part no more; the rounds stop when all are.

Neighbouring keys of a class agree in its width and in what the first two ranks that differ have in
common; that is looked up in the classes of the round before, and so on down, for all neighbours at once.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farpoint.llm.common import Staging

STEP = 4
STATE = "row_no long, doc_id long, live boolean, pos array<int>, rank array<long>, span array<int>, settled array<boolean>"
MOVES = "row_no long, at int, rank long, t1 long, t2 long, t3 long"


def in_order(stage: Staging, rows: DataFrame, group: str, order: list[str], value: str, table: str) -> DataFrame:
    """``rows`` with ``within``, the sum of ``value`` over the rows of the group before it, and the row's predecessor there as p_ columns.

    Rows are sorted over all machines by group and order, which have to tell them apart, so a group of any size
    is spread; the driver sees one row for each range.
    """
    fields = {f.name: f.dataType for f in rows.schema}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seq, total, last, opening = TaskContext.get().partitionId(), 0, 0, None, True
        for batch in batches:
            if not batch.num_rows:
                continue
            names = batch.schema.names
            g, v = batch.column(group).to_numpy(zero_copy_only=False), batch.column(value).to_numpy(zero_copy_only=False)
            new = np.concatenate([[last is None or g[0] != last.column(group)[0].as_py()], g[1:] != g[:-1]])
            before = np.concatenate([[0], np.cumsum(v)])
            starts = np.maximum.accumulate(np.where(new, np.arange(len(g)), -1))
            within = before[:-1] - np.where(starts >= 0, before[np.maximum(starts, 0)], -total)
            in_first = np.full(len(g), opening) & (np.cumsum(new) == (1 if seq == 0 else 0))
            opening = bool(in_first[-1])
            shifted = []
            for c in order:
                old = last.column(c) if last is not None else batch.column(c).slice(0, 1)
                moved = pa.concat_arrays([old, batch.column(c).slice(0, len(g) - 1)])
                shifted.append(pc.if_else(pa.array(new), pa.nulls(len(g), moved.type), moved))
            added = [pa.array(np.full(len(g), part, np.int32)), pa.array(np.arange(seq, seq + len(g))), pa.array(within.astype(np.int64)), pa.array(in_first), *shifted]
            yield pa.RecordBatch.from_arrays([*batch.columns, *added], names=[*names, "part", "seq", "within", "opening", *(f"p_{c}" for c in order)])
            total, seq, last = int(within[-1] + v[-1]), seq + len(g), batch.slice(len(g) - 1)

    kinds = ", ".join(f"{n} {t.simpleString()}" for n, t in fields.items()) + ", part int, seq long, within long, opening boolean, " + ", ".join(f"p_{c} {fields[c].simpleString()}" for c in order)
    made = stage.keep(rows.repartitionByRange(group, *order).sortWithinPartitions(group, *order).mapInArrow(run, kinds), table)
    ends = made.groupBy("part").agg(F.min(F.struct("seq", group)).alias("first"), F.max(F.struct("seq", group, *order, (F.col("within") + F.col(value)).alias("total"), "opening")).alias("last"))
    carried, held = [], None
    for r in sorted(ends.collect(), key=lambda r: r.part):  # a row for each range
        if held is not None and held[0] == r.first[1]:
            carried.append((r.part, held[1], *held[2]))
        total = r.last.total + (held[1] if held is not None and r.last.opening and held[0] == r.first[1] else 0)
        held = (r.last[1], total, tuple(r.last[2 : 2 + len(order)]))
    if not carried:
        return made.drop("part", "seq", "opening")
    schema = "part int, c_total long, " + ", ".join(f"c_{c} {fields[c].simpleString()}" for c in order)
    out = made.join(F.broadcast(stage.spark.createDataFrame(carried, schema)), "part", "left")
    out = out.withColumn("within", F.col("within") + F.when(F.col("opening"), F.coalesce("c_total", F.lit(0))).otherwise(0))
    for c in order:
        out = out.withColumn(f"p_{c}", F.when(F.col("seq") == 0, F.col(f"c_{c}")).otherwise(F.col(f"p_{c}")))
    return out.drop("part", "seq", "opening", "c_total", *(f"c_{c}" for c in order))


def left_over(pos: np.ndarray) -> np.ndarray:
    """For each line how many lines its sequence has from it on."""
    ends = np.flatnonzero(np.concatenate([pos[1:] != pos[:-1] + 1, [True]]))
    return ends[np.searchsorted(ends, np.arange(len(pos)))] - np.arange(len(pos)) + 1


def _numbers(column: pa.ListArray) -> list[np.ndarray]:
    flat, cuts = column.values.to_numpy(zero_copy_only=False), column.offsets.to_numpy()
    return [flat[a:b] for a, b in zip(cuts, cuts[1:], strict=False)]


def _state(batch: pa.RecordBatch, pos: list, rank: list, span: list, settled: list) -> pa.RecordBatch:
    live = pa.array([not bool(s.all()) for s in settled], pa.bool_())
    flat = pa.array(np.concatenate([np.empty(0, bool), *settled]), pa.bool_())
    cuts = pa.array(np.concatenate([[0], np.cumsum([len(p) for p in settled])]).astype(np.int32))
    ints = [pa.ListArray.from_arrays(cuts, pa.array(np.concatenate([np.empty(0, t), *x]).astype(t))) for x, t in ((pos, np.int32), (rank, np.int64), (span, np.int32))]
    return pa.RecordBatch.from_arrays([batch.column("row_no"), batch.column("doc_id"), live, *ints, pa.ListArray.from_arrays(cuts, flat)], names=["row_no", "doc_id", "live", "pos", "rank", "span", "settled"])


def _begun(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(row_no, doc_id, lines: [(pos, rank, span)] in order) -> STATE before the first round."""
    for batch in batches:
        pos, rank, span = [], [], []
        cuts, fields = batch.column("lines").offsets.to_numpy(), [f.to_numpy() for f in batch.column("lines").values.flatten()]
        for a, b in zip(cuts, cuts[1:], strict=False):
            for out, field in zip((pos, rank, span), fields, strict=True):
                out.append(field[a:b])
        yield _state(batch, pos, rank, span, [np.zeros(len(p), bool) for p in pos])


def _moves(width: int):
    """STATE -> MOVES: of each suffix that is not settled its rank and those further on, -1 behind the end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, ats, keys = [], [], []
            for row, pos, rank, settled in zip(batch.column("row_no").to_numpy(), *(_numbers(batch.column(c)) for c in ("pos", "rank", "settled")), strict=True):
                at, ends = np.flatnonzero(~settled.astype(bool)), left_over(pos)
                rows.append(np.full(len(at), row))
                ats.append(at)
                there = [np.where(j * width < ends[at], rank[np.minimum(at + j * width, len(rank) - 1)], -1) for j in range(1, STEP)]
                keys.append(np.stack([rank[at], *there]))
            key = np.concatenate([np.empty((STEP, 0), np.int64), *keys], axis=1)
            columns = [np.concatenate([np.empty(0, np.int64), *rows]), np.concatenate([np.empty(0, np.int64), *ats]).astype(np.int32), *key]
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(c)) for c in columns], names=["row_no", "at", "rank", "t1", "t2", "t3"])

    return run


def _moved(width: int):
    """STATE and moved: [(at, rank, n)] -> STATE at ``width``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pos, rank, span, settled = (_numbers(batch.column(c)) for c in ("pos", "rank", "span", "settled"))
            rank, settled = [r.copy() for r in rank], [s.astype(bool) for s in settled]
            cuts, fields = batch.column("moved").offsets.to_numpy(), [f.to_numpy() for f in batch.column("moved").values.flatten()]
            for i, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
                at, new, n = (f[a:b] for f in fields)
                rank[i][at] = new
                settled[i][at] = (n == 1) | (left_over(pos[i])[at] < width)
            yield _state(batch, pos, rank, span, settled)

    return run


def ordered_suffixes(stage: Staging, lines: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(row_no, doc_id, pos, line_hash, span) of all lines -> the suffixes (row_no, doc_id, pos, rank, rest, span) that begin
    with a line that stands twice, and (rank, common): how many lines a rank has in common with the one before it, where that is not 0.

    ``rest`` is how many lines there are to the end of the sequence. Suffixes of one rank are equal to their ends.
    """
    again = lines.groupBy("line_hash").agg(F.count("*").alias("n")).where("n > 1").withColumn("one", F.lit(0))
    # written, so that both sides of the join are plain exchanges and a hot line can be split
    names = in_order(stage, again, "one", ["line_hash"], "n", "names").select("line_hash", F.col("within").alias("rank"))
    repeated = lines.join(names.hint("merge"), "line_hash").select("row_no", "doc_id", F.struct("pos", "rank", "span").alias("line"))
    sequences = repeated.groupBy("row_no").agg(F.first("doc_id").alias("doc_id"), F.sort_array(F.collect_list("line")).alias("lines"))
    state = stage.keep(sequences.mapInArrow(_begun, STATE), "state")
    ended, classes, width = [state.where("NOT live")], [], 1
    while not (live := state.where("live")).isEmpty():
        moves = stage.keep(live.select("row_no", "pos", "rank", "settled").mapInArrow(_moves(width), MOVES), "moves")
        keys = moves.groupBy("rank", "t1", "t2", "t3").agg(F.count("*").alias("n"))
        known = in_order(stage, keys, "rank", ["t1", "t2", "t3"], "n", "classes")
        known = known.withColumn("new_rank", F.col("rank") + F.col("within")).drop("within")
        classes.append((width, known))
        width *= STEP
        found = moves.join(known.select("rank", "t1", "t2", "t3", "new_rank", "n").hint("merge"), ["rank", "t1", "t2", "t3"])
        found = found.groupBy("row_no").agg(F.collect_list(F.struct("at", F.col("new_rank").alias("rank"), "n")).alias("moved"))
        state = stage.keep(live.join(found.hint("merge"), "row_no").mapInArrow(_moved(width), STATE), "state")
        ended.append(state.where("NOT live"))
    out = None
    for done in ended:
        suffixes = done.select("row_no", "doc_id", "pos", "rank", "span").mapInArrow(_suffixes, "row_no long, doc_id long, pos int, rank long, rest int, span int")
        out = suffixes if out is None else out.unionByName(suffixes)
    return out, neighbours(stage, classes)


def _suffixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        pos, rank, span = (_numbers(batch.column(c)) for c in ("pos", "rank", "span"))
        owner = pa.array(np.repeat(np.arange(len(pos)), [len(p) for p in pos]))
        rest = np.concatenate([np.empty(0, np.int64), *map(left_over, pos)])
        columns = [np.concatenate([np.empty(0, t), *x]).astype(t) for x, t in ((pos, np.int32), (rank, np.int64), ([rest], np.int32), (span, np.int32))]
        yield pa.RecordBatch.from_arrays([batch.column("row_no").take(owner), batch.column("doc_id").take(owner), *map(pa.array, columns)], names=["row_no", "doc_id", "pos", "rank", "rest", "span"])


def _first_that_differ(common: Column, width: int, a: list[Column], b: list[Column]) -> Column:
    """The lines in common and the ranks there of the first components that differ."""
    cases = [F.struct((common + j * width).alias("common"), x.alias("a"), y.alias("b")) for j, (x, y) in enumerate(zip(a, b, strict=True), 1)]
    return F.when(a[0] != b[0], cases[0]).when(a[1] != b[1], cases[1]).otherwise(cases[2])


def neighbours(stage: Staging, classes: list[tuple[int, DataFrame]]) -> DataFrame:
    """(rank, common) of the ranks that a round made behind another one of the same class."""
    todo, done = None, None
    for level in range(len(classes) - 1, -1, -1):
        width, known = classes[level]
        beside = known.where("p_t1 IS NOT NULL")
        differ = _first_that_differ(F.lit(0).cast("long"), width, [F.col(f"p_t{j}") for j in (1, 2, 3)], [F.col(f"t{j}") for j in (1, 2, 3)])
        found = beside.select("new_rank", differ.alias("d")).select(F.col("new_rank").alias("rank"), "d.common", "d.a", "d.b")
        if todo is not None:  # these are of ranks that this round made
            sides = []
            for side in ("a", "b"):
                sides.append(known.select(F.col("new_rank").alias(side), F.col("rank").alias(f"{side}0"), *[F.col(f"t{j}").alias(f"{side}{j}") for j in (1, 2, 3)]).hint("merge"))
            both = todo.join(sides[0], "a", "left").join(sides[1], "b", "left")
            apart = F.struct("common", F.coalesce("a0", "a").alias("a"), F.coalesce("b0", "b").alias("b"))
            inside = _first_that_differ(F.col("common"), width, [F.col(f"a{j}") for j in (1, 2, 3)], [F.col(f"b{j}") for j in (1, 2, 3)])
            step = F.when(F.coalesce("a0", "a") != F.coalesce("b0", "b"), apart).otherwise(inside)
            found = found.unionByName(both.select("rank", step.alias("d")).select("rank", "d.common", "d.a", "d.b"))
        found = stage.keep(found, "neighbours")
        todo = found.where("a >= 0 AND b >= 0") if level else None
        ready = (found.where("a < 0 OR b < 0") if level else found).select("rank", "common")
        done = ready if done is None else done.unionByName(ready)
    return done if done is not None else stage.spark.createDataFrame([], "rank long, common long")
