"""Transcripts to canonical turns by a hidden Markov model over lines (operator 1).

A state is a role at the first line of a turn or within one. A line's symbol joins its
speaker marker's class, whether it asks, its length, and whether it opens its row. The model's
tables are smoothed counts over all labelled lines outside the holdout. Whether a line opens its
row counts only for lines without a role's marker, with probabilities of at least LEAN, so rows that hold
several turns, or parts of one, are parsed too. Viterbi runs over whole transcripts in
blocks of at most BLOCK rows, cut from all rows in order, so that many rows without a
position, or at the same one, are many blocks: each block gives the best score from any state before it to any
state at its end, a small matrix; the matrices of a transcript are chained, and each
block is then decoded between its two known states. So no task holds a transcript's lines.

A row is a piece of a transcript at a position (null: last), of one or more lines; rows at
the same position follow each other by text. Each row has an identity of its own, so equal
rows stay separate rows, in parse() and in by_row(). A row without an id belongs to no known
transcript and is one of its own. Null and empty texts are one empty line.
Markers that name a role are removed from the content; others are part of it.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize
from termatlas.llm.blocks import grouped

ROLES, BLOCK, LAST = ("system", "user", "assistant"), 256, (1 << 62)
STATES = len(ROLES) * 2  # role * 2 + (0 first line, 1 within)
# fixed values: names that speakers go by
NAMES = {"system": ("system", "sys", "instruction", "instructions"), "user": ("user", "human", "q", "question", "customer", "me"), "assistant": ("assistant", "bot", "ai", "a", "answer", "agent", "model")}
CLASS = {n: i for i, r in enumerate(ROLES) for n in NAMES[r]}
MARKER = re.compile(r"\s*(?:#{1,4}\s*|\[|<\|?|\*\*)?([A-Za-z]{1,14})(?:\]|\|?>|\*\*)?\s*:\s?")
OTHER, NONE, SYMBOLS = 3, 4, 5 * 2 * 4 * 2
#: the least probability that a line opens its row, or doesn't, in any state
LEAN = 0.05


def marker(line: str) -> tuple[int, int]:
    """The marker's class and where the content starts."""
    m = MARKER.match(line)
    if not m:
        return NONE, 0
    found = CLASS.get(m[1].lower(), OTHER)
    return found, m.end() if found < OTHER else 0


def symbol(line: str, opens: bool) -> int:
    n = len(line)
    return ((marker(line)[0] * 2 + ("?" in line)) * 4 + (n > 0) + (n > 40) + (n > 160)) * 2 + opens


@dataclass
class Model:
    start: np.ndarray  # log, by state
    move: np.ndarray  # log, state by state
    emit: np.ndarray  # log, state by symbol

    @classmethod
    def of(cls, start: np.ndarray, move: np.ndarray, emit: np.ndarray, smooth: float = 0.5) -> Model:
        log = lambda x, s=smooth: np.log((x + s) / (x + s).sum(axis=-1, keepdims=True))
        first = np.arange(STATES) % 2 == 0
        start, move = log(start), log(move)
        start[~first] = -1e9  # a transcript starts with a turn
        for s in range(STATES):
            for t in range(STATES):
                if t % 2 and t // 2 != s // 2:
                    move[s, t] = -1e9  # a turn keeps its role
        # a line's parts are taken as independent: rare combinations keep what each part says
        by_part = emit.reshape(STATES, 5, 2, 4, 2)
        marks, asks, sizes = log(by_part.sum(axis=(2, 3, 4)), smooth / 20), log(by_part.sum(axis=(1, 3, 4))), log(by_part.sum(axis=(1, 2, 4)))
        every = (marks[:, :, None, None, None] + asks[:, None, :, None, None] + sizes[:, None, None, :, None]).repeat(2, axis=4)
        # a role's marker tells by itself that a turn begins: the place in the row tells of other lines only
        opens = np.log(LEAN + (1 - 2 * LEAN) * np.exp(log(by_part[:, OTHER:].sum(axis=(1, 2, 3)))))
        every[:, OTHER:] += opens[:, None, None, None, :]
        return cls(start, move, every.reshape(STATES, SYMBOLS))

    def through(self, seen: np.ndarray, initial: bool) -> np.ndarray:
        """Best scores from each state before the lines (one row for the start) to each state at their end."""
        at = (self.start[None, :] if initial else self.move) + self.emit[:, seen[0]]
        for o in seen[1:]:
            at = (at[:, :, None] + self.move[None]).max(axis=1) + self.emit[:, o]
        return at

    def path(self, seen: np.ndarray, before: int, end: int) -> np.ndarray:
        """The best states between the state before (-1: the start) and the end state (-1: any)."""
        at, back = (self.start if before < 0 else self.move[before]) + self.emit[:, seen[0]], []
        for o in seen[1:]:
            step = at[:, None] + self.move
            back.append(step.argmax(axis=0))
            at = step.max(axis=0) + self.emit[:, o]
        out = [int(at.argmax()) if end < 0 else end]
        for b in reversed(back):
            out.append(int(b[out[-1]]))
        return np.array(out[::-1])


def lines(text: str | None) -> list[str]:
    return (text or "").split("\n")


def held_out(key: str) -> Column:
    return F.pmod(F.xxhash64(F.col(key), F.lit(3)), F.lit(5)) == 0


def fit(pieces: DataFrame) -> Model:
    """The model from pieces: id, seq, text, role (rows of other roles, or held out, are not used)."""
    own = pieces.where(F.col("role").isin(*ROLES) & ~held_out("id"))

    def count(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: Counter = Counter()
        for frame in frames:
            for text, role in zip(frame.text, frame.role, strict=True):
                r = ROLES.index(role)
                each = lines(text)
                for i, line in enumerate(each):
                    seen["emit", 2 * r + (i > 0), symbol(line, i == 0)] += 1
                if len(each) > 1:
                    seen["move", 2 * r, 2 * r + 1] += 1
                    seen["move", 2 * r + 1, 2 * r + 1] += len(each) - 2
        yield pd.DataFrame([(k, a, b, n) for (k, a, b), n in seen.items()], columns=["kind", "a", "b", "n"])

    single = F.size(F.split(F.coalesce("text", F.lit("")), "\n", -1)) == 1
    code = F.array_position(F.array(*map(F.lit, ROLES)), F.col("role")) - 1
    turns = own.select("id", "seq", (code * 2 + F.when(single, 0).otherwise(1)).alias("last"), (code * 2).alias("first")).distinct()
    after = turns.select("id", (F.col("seq") - 1).alias("seq"), F.col("first").alias("b"))
    between = turns.join(after, ["id", "seq"]).groupBy(F.lit("move").alias("kind"), F.col("last").alias("a"), "b").agg(F.count("*").alias("n"))
    opening = own.where(F.col("id").isNotNull()).groupBy("id").agg(F.min_by(code * 2, "seq").alias("b")).groupBy(F.lit("start").alias("kind"), F.lit(0).alias("a"), "b").agg(F.count("*").alias("n"))
    inside = own.select("text", "role").mapInPandas(count, "kind string, a int, b int, n long")
    start, move, emit = np.zeros(STATES), np.zeros((STATES, STATES)), np.zeros((STATES, SYMBOLS))
    for r in inside.unionByName(between).unionByName(opening).groupBy("kind", "a", "b").agg(F.sum("n").alias("n")).collect():
        if r.kind == "start":
            start[r.b] += r.n
        else:
            (move if r.kind == "move" else emit)[r.a, r.b] += r.n
    return Model.of(start, move, emit)


def dealt_rows(pieces: DataFrame) -> DataFrame:
    """row, transcript, id, seq, text, block, place: the rows in order of transcript and position, in blocks of at most BLOCK.

    Rows are dealt by ranges of the whole order, ties told apart by row, so neither a long transcript nor a common position stays in one task.
    Blocks follow the order; a block ends where its transcript or its range ends.
    """
    row = F.col("row").cast("string")
    rows = pieces.select("id", F.col("seq").cast("long").alias("seq"), F.coalesce("text", F.lit("")).alias("text")).withColumn("row", F.monotonically_increasing_id())
    rows = rows.select("row", F.coalesce(F.concat(F.lit("id "), F.col("id").cast("string")), F.concat(F.lit("row "), row)).alias("transcript"), "id", "seq", "text")
    order = [F.col("transcript"), F.col("seq").asc_nulls_last(), F.col("text"), F.col("row")]
    # the rows' numbers are written before they are dealt: a range's bounds are sampled from the same rows
    spread = materialize(rows, "rows").repartitionByRange(*order).sortWithinPartitions(*order).withColumn("part", F.spark_partition_id())

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, block, place = None, -1, 0
        for batch in batches:
            blocks, places = [], []
            base = batch.column("part")[0].as_py() << 40 if batch.num_rows else 0
            for t in batch.column("transcript").to_pylist():
                place += 1
                if t != last or place == BLOCK:
                    last, block, place = t, block + 1, 0
                blocks.append(base + block), places.append(place)
            kept = [batch.column(n) for n in batch.schema.names if n != "part"]
            yield pa.RecordBatch.from_arrays([*kept, pa.array(blocks, pa.int64()), pa.array(places, pa.int32())], names=[*(n for n in batch.schema.names if n != "part"), "block", "place"])

    kind = pieces.schema["id"].dataType.simpleString()
    return materialize(spread.mapInArrow(number, f"row long, transcript string, id {kind}, seq long, text string, block long, place int"), "dealt")


def parse(pieces: DataFrame, model: Model) -> DataFrame:
    """row (its identity), id, seq, line (within the row), role, begins, content: one row for each line of pieces (id, seq, text)."""
    rows = dealt_rows(pieces)
    key = ["transcript", "block"]
    first = rows.groupBy("transcript").agg(F.min("block").alias("opening"))
    dealt = rows.join(first, "transcript").select(*key, "place", "row", "text", (F.col("block") == F.col("opening")).alias("initial"))
    order = [*key, "place"]

    def seen_of(group: pd.DataFrame) -> np.ndarray:
        return np.array([symbol(x, i == 0) for t in group.text for i, x in enumerate(lines(t))])

    def chain(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def each(group: pd.DataFrame) -> pd.DataFrame:
            m = model.through(seen_of(group), bool(group.initial.iloc[0]))
            return pd.DataFrame({"transcript": [group.transcript.iloc[0]], "block": [group.block.iloc[0]], "m": [m.ravel()]})

        yield from grouped(frames, key, each)

    def walk(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def each(group: pd.DataFrame) -> pd.DataFrame:
            ms = [np.asarray(m).reshape(-1, STATES) for m in group.m]
            at, back = ms[0][0], []
            for m in ms[1:]:
                step = at[:, None] + m
                back.append(step.argmax(axis=0))
                at = step.max(axis=0)
            ends = [int(at.argmax())]
            for b in reversed(back):
                ends.append(int(b[ends[-1]]))
            ends.reverse()
            return pd.DataFrame({"transcript": group.transcript.to_numpy(), "block": group.block.to_numpy(), "before": [-1, *ends[:-1]], "end": ends})

        yield from grouped(frames, ["transcript"], each)

    def decode(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def each(group: pd.DataFrame) -> pd.DataFrame:
            path = model.path(seen_of(group), int(group.before.iloc[0]), int(group.end.iloc[0]))
            out, k = [], 0
            for row, t in zip(group.row, group.text, strict=True):
                for n, x in enumerate(lines(t)):
                    out.append((row, n, ROLES[path[k] // 2], path[k] % 2 == 0, x[marker(x)[1] :]))
                    k += 1
            return pd.DataFrame(out, columns=["row", "line", "role", "begins", "content"])

        yield from grouped(frames, key, each)

    inside = dealt.repartition(*key).sortWithinPartitions(*order)
    blocks = materialize(inside.mapInPandas(chain, "transcript string, block long, m array<double>"), "chains")
    ends = blocks.repartition("transcript").sortWithinPartitions(*key).mapInPandas(walk, "transcript string, block long, before int, end int")
    joined = dealt.join(ends, key).repartition(*key).sortWithinPartitions(*order)
    decoded = joined.select(*key, "row", "text", "before", "end").mapInPandas(decode, "row long, line int, role string, begins boolean, content string")
    return rows.select("row", "id", "seq").join(decoded, "row")


def render(role: str | Column, content: str | Column) -> Column:
    """A canonical turn."""
    role, content = (F.col(x) if isinstance(x, str) else x for x in (role, content))
    return F.concat(F.lit("<|"), role, F.lit("|>\n"), content, F.lit("\n<|end|>\n"))


def by_row(parsed: DataFrame) -> DataFrame:
    """id, seq, recovered (role of the row's first line), begins, n_lines, rendered: canonical form of each row's lines, one for each row that was parsed.

    Lines of a row that begin further turns, or roles, are rendered as turns of their own.
    """
    own = parsed.groupBy("row", "id", "seq").agg(F.array_sort(F.collect_list(F.struct("line", "role", "begins", "content"))).alias("x"))
    start = F.struct(F.lit("").alias("role"), F.lit("").alias("text"))

    def add(s: Column, x: Column) -> Column:
        opened = F.concat(F.when(s["role"] == "", F.lit("")).otherwise(F.concat(s["text"], F.lit("\n<|end|>\n"))), F.lit("<|"), x["role"], F.lit("|>\n"), x["content"])
        return F.struct(x["role"].alias("role"), F.when(x["begins"] | (s["role"] == ""), opened).otherwise(F.concat(s["text"], F.lit("\n"), x["content"])).alias("text"))

    text = F.aggregate("x", start, add, lambda s: F.concat(s["text"], F.lit("\n<|end|>\n")))
    return own.select("id", "seq", F.col("x")[0]["role"].alias("recovered"), F.col("x")[0]["begins"].alias("begins"), F.size("x").cast("long").alias("n_lines"), text.alias("rendered"))


# fixed values: how the transcripts of the query write speakers
STYLES = {"system": ("System: ", "### System: ", "[sys]: "), "user": ("User: ", "Human: ", "### User: ", "Q: "), "assistant": ("Assistant: ", "Bot: ", "**AI**: ", "A: ")}


def transcribe(conversations: DataFrame, unmarked: int = 10) -> DataFrame:
    """id, seq, text, role: turns as a raw transcript writes them, `unmarked` percent of them without a marker."""
    draw = F.pmod(F.xxhash64("conv_id", "turn", F.lit(5)), F.lit(100))
    style = F.pmod(F.xxhash64("conv_id", F.lit(6)), F.lit(12))
    mark = F.lit("")
    for role, names in STYLES.items():
        mark = F.when(F.col("role") == role, F.element_at(F.array(*map(F.lit, names)), (F.pmod(style, F.lit(len(names))) + 1).cast("int"))).otherwise(mark)
    text = F.concat(F.when(draw < unmarked, F.lit("")).otherwise(mark), F.coalesce("text", F.lit("")))
    return conversations.select(F.col("conv_id").alias("id"), F.col("turn").cast("long").alias("seq"), text.alias("text"), "role")
