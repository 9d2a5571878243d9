"""Replace-minimum counter summaries of cells per term.

A summary row holds, for one term: total arrivals, capacity, policy, replacements, whether
centres are frozen, and centres (cell, f, err, rings, born_seq) ordered by (f desc, err asc,
cell asc). The smallest counter to be replaced is the one lowest by (f, cell).

`build` replays arrivals in order inside one task per (term, pane): rows are shuffled once,
sorted, collapsed in runs and streamed, so no group has to fit in memory. Panes cut a hot
term into parts that are summarised apart and merged; the error bound N / m then holds
for the merge as for a single summary, but order inside the term is that of the panes.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

CENTRE = "struct<cell:int,f:bigint,err:bigint,rings:array<double>,born_seq:bigint>"
SUMMARY = f"term string, total long, capacity int, policy string, n_replaced long, frozen boolean, centers array<{CENTRE}>"


def capacity(eps: float) -> int:
    """Counters that keep every cell with a share of eps or more."""
    return math.ceil(1 / eps - 1e-9)


class Counters:
    """The core: at most `capacity` counters, in plain Python.

    Each counter has one entry in a heap, which may lag behind it; entries are brought up to date when
    they come to the top, so finding the smallest takes a logarithm of the counters, amortised.
    """

    def __init__(self, capacity: int):
        self.capacity, self.total, self.replaced = capacity, 0, 0
        self.f: dict[int, int] = {}
        self.err: dict[int, int] = {}
        self.born: dict[int, int] = {}
        self.heap: list[tuple[int, int]] = []

    def lowest(self) -> int:
        heap, f = self.heap, self.f
        while heap[0][0] != f[heap[0][1]]:
            heapq.heapreplace(heap, (f[heap[0][1]], heap[0][1]))
        return heap[0][1]

    def observe(self, cell: int, n: int = 1, seq: int = 0) -> int | None:
        """Count n arrivals in a row at a cell; the cell that lost its counter, if one did."""
        self.total += n
        if cell in self.f:
            self.f[cell] += n
            return None
        self.born[cell] = seq
        if len(self.f) < self.capacity:
            self.f[cell], self.err[cell] = n, 0
            heapq.heappush(self.heap, (n, cell))
            return None
        victim = self.lowest()
        self.err[cell] = self.f.pop(victim)
        self.f[cell] = self.err[cell] + n
        heapq.heapreplace(self.heap, (self.f[cell], cell))
        del self.err[victim], self.born[victim]
        self.replaced += 1
        return victim

    def observe_all(self, cells: np.ndarray, sizes: np.ndarray, seqs: np.ndarray) -> None:
        f, observe, seen = self.f, self.observe, 0
        for c, n, s in zip(cells.tolist(), sizes.tolist(), seqs.tolist(), strict=True):
            if c in f:
                f[c] += n
                seen += n
            else:
                observe(c, n, s)
        self.total += seen

    def row(self, term: str, policy: str = "counter") -> dict:
        order = sorted(self.f, key=lambda c: (-self.f[c], self.err[c], c))
        centres = [{"cell": int(c), "f": int(self.f[c]), "err": int(self.err[c]), "rings": [], "born_seq": int(self.born[c])} for c in order]
        return {"term": term, "total": int(self.total), "capacity": self.capacity, "policy": policy, "n_replaced": int(self.replaced), "frozen": False, "centers": centres}


def collapse_runs(occ: DataFrame) -> DataFrame:
    """term, pane, cell, seq (first of the run), n: consecutive equal arrivals of a term as one; replays are unchanged.

    Needs columns term, pane, cell, ts, seq, msg_id.
    """
    order = Window.partitionBy("term", "pane").orderBy("ts", "seq", "msg_id", "cell")
    new = F.coalesce((F.lag("cell").over(order) != F.col("cell")).cast("int"), F.lit(1))
    runs = occ.withColumn("new", new).withColumn("run", F.sum("new").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return runs.groupBy("term", "pane", "run").agg(F.first("cell").alias("cell"), F.min("seq").alias("seq"), F.count("*").alias("n"))


PIECE, FLAT = 256, 1 << 16


def gathered(occ: DataFrame) -> DataFrame:
    """term, part, cells, seqs: each term's arrivals in order, PIECE at most a row, so that several replays need one sort.

    Tasks take ranges of (term, time), so that the arrivals of a frequent term are sorted by several.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId() << 40  # tasks are in order
        for batch in batches:
            if not batch.num_rows:
                continue
            starts = _pieces(batch.column("term").dictionary_encode().indices.to_numpy())
            offsets = pa.array(np.append(starts, batch.num_rows), pa.int32())
            cells, seqs = (pa.ListArray.from_arrays(offsets, batch.column(k)) for k in ("cell", "seq"))
            yield pa.RecordBatch.from_arrays([batch.column("term").take(pa.array(starts)), pa.array(part + np.arange(len(starts)), pa.int64()), cells, seqs], ["term", "part", "cells", "seqs"])
            part += len(starts)

    rows = occ.where(F.col("term").isNotNull() & F.col("cell").isNotNull()).select("term", "cell", "ts", "seq", "msg_id")
    tasks, by = int(occ.sparkSession.conf.get("spark.sql.shuffle.partitions")), ["term", "ts", "seq", "msg_id", "cell"]
    return rows.repartitionByRange(tasks, *by).sortWithinPartitions(*by).select("term", "cell", "seq").mapInArrow(run, "term string, part long, cells array<int>, seqs array<long>")


def _pieces(key: np.ndarray) -> np.ndarray:
    """Where pieces of equal keys in a row begin, PIECE at most each."""
    ends = np.append(np.flatnonzero(np.diff(key)) + 1, len(key))
    return np.concatenate([np.arange(a, b, PIECE) for a, b in zip(np.append(0, ends[:-1]), ends, strict=True)])


def coded_messages(docs: DataFrame, terms: list[str]) -> DataFrame:
    """Messages with a cell (seq, ts, msg_id, cell) and the places in `terms`, which are few, of their distinct terms."""
    value_set = pa.array(terms, pa.string())

    def coded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column("terms")
            code = pc.index_in(lists.flatten(), value_set=value_set)
            there = pc.is_valid(code).to_numpy(zero_copy_only=False)
            size = np.bincount(pc.list_parent_indices(lists).to_numpy()[there], minlength=len(lists))
            offsets = pa.array(np.concatenate([[0], np.cumsum(size)]), pa.int32())
            codes = pa.ListArray.from_arrays(offsets, code.drop_null())
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in ("ts", "seq", "msg_id", "cell")), codes], ["ts", "seq", "msg_id", "cell", "codes"])

    some = docs.where(F.col("cell").isNotNull()).select("ts", "seq", "msg_id", "cell", "terms")
    return some.mapInArrow(coded, "ts timestamp, seq long, msg_id long, cell int, codes array<int>").where(F.size("codes") > 0)


def gathered_messages(codes: DataFrame, terms: list[str]) -> DataFrame:
    """`gathered` of coded messages. Messages are put in order, not their arrivals; each task then deals its messages' cells out to the terms."""
    value_set = pa.array(terms, pa.string())

    def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part = TaskContext.get().partitionId() << 40  # tasks are in order
        for batch in batches:
            lists = batch.column("codes")
            code = lists.flatten().to_numpy()
            if not len(code):
                continue
            order = np.argsort(code, kind="stable")
            at = pa.array(pc.list_parent_indices(lists).to_numpy()[order])
            code = code[order]
            starts = _pieces(code)
            offsets = pa.array(np.append(starts, len(code)), pa.int32())
            cells, seqs = (pa.ListArray.from_arrays(offsets, batch.column(k).take(at)) for k in ("cell", "seq"))
            parts = pa.array(part + np.arange(len(starts)), pa.int64())
            yield pa.RecordBatch.from_arrays([value_set.take(pa.array(code[starts])), parts, cells, seqs], ["term", "part", "cells", "seqs"])
            part += len(starts)

    tasks, by = int(codes.sparkSession.conf.get("spark.sql.shuffle.partitions")), ["ts", "seq", "msg_id", "cell"]
    return codes.repartitionByRange(tasks, *by).sortWithinPartitions(*by).mapInArrow(dealt, "term string, part long, cells array<int>, seqs array<long>")


def counts_of_gathered(rows: DataFrame) -> DataFrame:
    """term, cell, n of gathered arrivals."""
    return rows.select("term", F.explode("cells").alias("cell")).groupBy("term", "cell").agg(F.count("*").alias("n"))


def _flat(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Gathered arrivals one a row."""
    step = FLAT // PIECE
    for frame in frames:
        for at in range(0, len(frame), step):
            part = frame.iloc[at : at + step]
            size = part.cells.map(len).to_numpy()
            yield pd.DataFrame({"term": np.repeat(part.term.to_numpy(), size), "pane": np.repeat(part.pane.to_numpy(), size) if "pane" in part.columns else 0, "cell": np.concatenate(part.cells.to_list()), "seq": np.concatenate(part.seqs.to_list())})


def arrivals(occ: DataFrame, panes: int = 1) -> DataFrame:
    """term, pane, cell, seq, dealt by (term, pane) and sorted by arrival inside; cells are never null. Gathered ones stay gathered."""
    if "cells" in occ.columns:
        if panes > 1:
            raise ValueError("gathered arrivals have no panes")
        tasks = int(occ.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return occ.repartition(tasks, "term").sortWithinPartitions("term", "part").select("term", *(["pane"] if "pane" in occ.columns else []), "cells", "seqs")
    pane = F.lit(0) if panes == 1 else F.pmod(F.xxhash64("msg_id", "seq"), F.lit(panes)).cast("int")
    rows = occ.where(F.col("term").isNotNull() & F.col("cell").isNotNull()).select("term", pane.alias("pane"), "cell", "ts", "seq", "msg_id")
    # a replay is long for its few bytes, so tasks are not merged by size
    tasks = int(occ.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(tasks, "term", "pane").sortWithinPartitions("term", "pane", "ts", "seq", "msg_id", "cell").select("term", "pane", "cell", "seq")


def replay(frames: Iterator[pd.DataFrame], new, finish) -> Iterator[pd.DataFrame]:
    """Stream sorted arrivals: new(term, pane) makes a state with observe_all(cells, sizes, seqs); finish(state, term) makes its row."""
    state = at = None
    frames = (x for frame in frames for x in (_flat([frame]) if "cells" in frame.columns else [frame]))
    for frame in frames:
        if not len(frame):
            continue
        term, pane, cell = frame.term.to_numpy(), frame.pane.to_numpy(), frame.cell.to_numpy()
        other = np.concatenate([[True], (term[1:] != term[:-1]) | (pane[1:] != pane[:-1])])
        starts = np.flatnonzero(other | np.concatenate([[True], cell[1:] != cell[:-1]]))
        runs = cell[starts], np.diff(np.append(starts, len(frame))), frame.seq.to_numpy()[starts]
        groups = np.flatnonzero(other[starts])
        done = []
        for a, b in zip(groups.tolist(), [*groups[1:].tolist(), len(starts)], strict=True):
            key = term[starts[a]], pane[starts[a]]
            if at != key:
                if state is not None:
                    done.append(finish(state, at[0]))
                at, state = key, new(*key)
            state.observe_all(*(x[a:b] for x in runs))
        if done:
            yield pd.DataFrame(done)
    if state is not None:
        yield pd.DataFrame([finish(state, at[0])])


def build(occ: DataFrame, capacity: int, panes: int = 1) -> DataFrame:
    """SUMMARY of each term of occ."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        yield from replay(frames, lambda *_: Counters(capacity), lambda s, t: s.row(t))

    parts = arrivals(occ, panes).mapInPandas(run, SUMMARY)
    return parts if panes == 1 else merge(parts, capacity)


def merge(summaries: DataFrame, capacity: int) -> DataFrame:
    """One SUMMARY per term of several: sums, absent cells counted with their summary's smallest counter, the largest kept.

    A counter's f stays at least its true count, f - err at most; sums of counters may then pass the total.
    Bands are summed over the summaries that hold the cell and scaled by the arrivals of all: parts that are
    dealt by hash see the same distribution, so this is an estimate without bias, but without a bound.
    """
    one = summaries.select("term", "total", "n_replaced", "centers", absent_bound().alias("bound"))
    sums = one.groupBy("term").agg(F.sum("total").alias("total"), F.sum("n_replaced").alias("n_replaced"), F.sum("bound").alias("bounds"))
    add = lambda a, b: F.zip_with(a, b, lambda x, y: F.coalesce(x, F.lit(0.0)) + F.coalesce(y, F.lit(0.0)))
    rings = F.aggregate(F.collect_list("c.rings"), F.array().cast("array<double>"), add).alias("rings")
    held = one.select("term", "bound", "total", F.explode("centers").alias("c")).groupBy("term", "c.cell")
    cells = held.agg(F.sum("c.f").alias("f"), F.sum("c.err").alias("err"), F.sum("bound").alias("known"), F.sum("total").alias("seen"), F.min("c.born_seq").alias("born_seq"), rings)
    cells = cells.join(sums.select("term", "bounds", F.col("total").alias("every")), "term").withColumn("more", F.col("bounds") - F.col("known"))
    scaled = F.transform("rings", lambda x: x * F.col("every") / F.col("seen")).alias("rings")
    cells = cells.select("term", "cell", (F.col("f") + F.col("more")).alias("f"), (F.col("err") + F.col("more")).alias("err"), "born_seq", scaled)
    best = cells.withColumn("rank", F.row_number().over(Window.partitionBy("term").orderBy(F.desc("f"), "err", "cell"))).where(F.col("rank") <= capacity)
    centre = F.struct("rank", F.struct("cell", "f", "err", "rings", "born_seq").alias("c"))
    rows = best.groupBy("term").agg(F.transform(F.array_sort(F.collect_list(centre)), lambda x: x["c"]).alias("centers"))
    out = rows.join(sums, "term").select("term", "total", F.lit(capacity).alias("capacity"), F.lit("merged").alias("policy"), "n_replaced", F.lit(False).alias("frozen"), F.col("centers").cast(f"array<{CENTRE}>").alias("centers"))
    return out


def windowed(occ: DataFrame, capacity: int, size: str = "7 days", slide: str = "1 day") -> DataFrame:
    """SUMMARY per term and sliding window (with column window_start): one summary a slide, merged over the windows that hold it."""
    panes = occ.withColumn("slide", F.window("ts", slide)["start"]).withColumn("key", F.concat_ws("\x1f", "term", F.unix_micros("slide").cast("string")))
    parts = build(panes.withColumn("term", F.col("key")), capacity)
    term, start = F.substring_index("term", "\x1f", 1), F.timestamp_micros(F.substring_index("term", "\x1f", -1).cast("long"))
    parts = parts.withColumn("window_start", F.explode(F.sequence(start - F.expr(f"interval {size}") + F.expr(f"interval {slide}"), start, F.expr(f"interval {slide}")))).withColumn("term", F.concat_ws("\x1f", term, F.unix_micros("window_start").cast("string")))
    merged = merge(parts.drop("window_start"), capacity)
    return merged.withColumn("window_start", start).withColumn("term", term)


def exploded(summary: DataFrame) -> DataFrame:
    """CENTERS: term, total, rank (from 1), cell, f, err, rings."""
    return summary.select("term", "total", F.posexplode("centers").alias("pos", "c")).select("term", "total", (F.col("pos") + 1).alias("rank"), "c.cell", "c.f", "c.err", "c.rings")


def absent_bound(centers: str = "centers", capacity: str = "capacity") -> Column:
    """Most arrivals a cell without a counter can have had: the smallest counter, 0 while there is room."""
    return F.when(F.size(centers) >= F.col(capacity), F.array_min(F.transform(centers, lambda c: c["f"]))).otherwise(F.lit(0)).cast("long")


def total(centers: str = "centers") -> Column:
    """Sum of the counters: the term's arrivals, where every arrival counts in one (not when frozen or skipping)."""
    return F.aggregate(centers, F.lit(0).cast("long"), lambda s, c: s + c["f"])


def largest_error(centers: str = "centers") -> Column:
    return F.coalesce(F.array_max(F.transform(centers, lambda c: c["err"])), F.lit(0).cast("long"))


def error_bound(summary: DataFrame) -> DataFrame:
    """term, largest_error, allowed = total / capacity, holds."""
    allowed = F.col("total") / F.col("capacity")
    return summary.select("term", largest_error().alias("largest_error"), allowed.alias("allowed"), (largest_error() <= allowed).alias("holds"))


def heavy_terms(occ: DataFrame, share: float) -> DataFrame:
    """term, n: terms that occur in at least this share of the messages."""
    n = occ.select("msg_id").distinct().agg(F.count("*").alias("messages"))
    by = occ.groupBy("term").agg(F.count_distinct("msg_id").alias("n"))
    return by.join(F.broadcast(n), F.col("n") >= F.lit(share) * F.col("messages")).select("term", "n")


def heavy_gathered(docs: DataFrame, share: float) -> DataFrame:
    """heavy_terms of messages with their distinct terms in an array (msg_id, terms).

    Where no message id occurs twice, a term's messages are its arrivals, and no pair of term and message is shuffled.
    """
    # where the number of a message's terms is a column, its terms are not read to find whether there are any
    some = docs.where((F.col("n_terms") if "n_terms" in docs.columns else F.size("terms")) > 0)
    rows, ids = some.agg(F.count("msg_id"), F.count_distinct("msg_id")).first()
    occ = some.select("msg_id", F.explode("terms").alias("term"))
    if rows != ids:
        return heavy_terms(occ, share)
    counted = occ.where(F.col("msg_id").isNotNull()).groupBy("term").agg(F.count("*").alias("n"))
    # heavy_terms counts null as one message, which holds terms no more than null is counted
    messages = ids + some.where(F.col("msg_id").isNull()).limit(1).count()
    return counted.where(F.col("n") >= F.lit(share) * F.lit(messages)).select("term", "n")


def only_heavy(occ: DataFrame, share: float) -> DataFrame:
    return occ.join(heavy_terms(occ, share).select("term"), "term", "left_semi")
