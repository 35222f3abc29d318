"""Chat formatting: a hidden Markov model recovers speakers from raw transcripts, then turns are rendered canonically.

A transcript is lines of text. Hidden states are (role, begins a turn or goes on); what is seen of a line is its speaker
marker, if any, and a few features. Emissions, and how speakers begin and follow each other, are counted over all
labelled lines given. Viterbi's best path gives the roles, and runs of lines become turns in one format.

A conversation is decoded in chunks of CHUNK turns. Where it has several, each chunk first yields its max-plus matrix
(best path score from any state before it to any state at its end); these compose, so the states at the chunks' ends
are those of the best path of the whole conversation, and chunks are then decoded on their own. A long conversation is
thus spread over tasks and never held by one.

Defined cases: a null text is one empty line; a null role counts for no emission; equal repeated turns (id, turn, role,
text) count once; equal turn numbers go by text; turns without number come first; rows without conversation id form one
conversation; an empty table gives no turns.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window
from pyspark.sql.pandas.types import to_arrow_type

from .common import cut, lean

CHUNK = 256
ROLES = ["system", "user", "assistant"]
#: Markers of common transcript styles by role; fixed values.
STYLES = [
    {"system": "System: ", "user": "User: ", "assistant": "Assistant: "},
    {"system": "Context: ", "user": "Human: ", "assistant": "AI: "},
    {"system": "### System ", "user": "### User ", "assistant": "### Assistant "},
    {"system": "<|system|>", "user": "<|user|>", "assistant": "<|assistant|>"},
    {"system": "Note: ", "user": "Q: ", "assistant": "A: "},
]
MARKS, SYMBOLS = 4, 4 * 2 * 2 * 4


def _marker(line: Column) -> Column:
    """0: none, else 1 + the role's place in ROLES."""
    out = F.lit(0)
    for k, role in enumerate(ROLES):
        for style in STYLES:
            out = F.when(line.startswith(style[role]), k + 1).otherwise(out)
    return out


def symbol(line: Column) -> Column:
    """What is seen of a line, as an integer below SYMBOLS."""
    n = F.length(line)
    size = F.when(n < 20, 0).when(n < 80, 1).when(n < 200, 2).otherwise(3)
    asks, capital = line.rlike(r"\?\s*$").cast("int"), line.rlike(r"^\p{Lu}").cast("int")
    return (((_marker(line) * 2 + asks) * 2 + capital) * 4 + size).cast("int")


def transcript_lines(turns: DataFrame, unmarked: int = 20) -> DataFrame:
    """Raw transcripts of stored conversations, a row per line: each conversation has one marker style, and a twentieth
    of the turns has no marker. ``true_state`` is 2 * role + (line goes on)."""
    each = turns.select("conv_id", "turn", "role", F.coalesce("text", F.lit("")).alias("text")).distinct()
    seed = F.crc32(F.coalesce(F.col("conv_id").cast("string"), F.lit("null")).cast("binary"))
    mark = F.lit("")
    for i, style in enumerate(STYLES):
        for role, text in style.items():
            mark = F.when((seed % len(STYLES) == i) & (F.col("role") == role), text).otherwise(mark)
    bare = F.crc32(F.concat_ws("|", F.col("conv_id").cast("string"), F.col("turn").cast("string")).cast("binary")) % unmarked == 0
    each = each.withColumn("marked", F.concat(F.when(bare, "").otherwise(mark), F.col("text"))).withColumn("tie", F.xxhash64("text", "role"))
    lines = each.select("conv_id", "turn", "tie", "role", F.posexplode(F.split("marked", "\n")).alias("line_no", "line"))
    state = F.when(F.col("role").isin(ROLES), 2 * (F.array_position(F.lit(ROLES), F.col("role")) - 1).cast("int") + (F.col("line_no") > 0).cast("int"))
    return lines.withColumn("symbol", symbol(F.col("line"))).withColumn("true_state", state)


def chunked(lines: DataFrame, chunk_turns: int = CHUNK) -> DataFrame:
    """Adds the chunk of a line: its turn's number over ``chunk_turns``, -1 for turns without a number."""
    number = F.expr("try_cast(turn AS double)")
    return lines.withColumn("chunk", F.coalesce(F.floor(number / chunk_turns), F.lit(-1)).cast("long"))


def role_steps(lines: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """How many conversations begin with each role, and how often a turn of a role is followed by one of another: within
    chunks by a window, over chunks' borders by a row per chunk, so that no conversation is held by one task."""
    turns = chunked(lines).where("line_no = 0 and true_state is not null").select("conv_id", "chunk", "turn", "tie", F.floor(F.col("true_state") / 2).cast("int").alias("role"))
    inside = Window.partitionBy("conv_id", "chunk").orderBy("turn", "tie")
    place = F.struct("turn", "tie")
    ends = turns.groupBy("conv_id", "chunk").agg(F.min_by("role", place).alias("role"), F.max_by("role", place).alias("last"))
    along = Window.partitionBy("conv_id").orderBy("chunk")
    pairs = turns.select(F.lag("role").over(inside).alias("a"), F.col("role").alias("b")).where("a is not null")
    pairs = pairs.unionAll(ends.select(F.coalesce(F.lag("last").over(along), F.lit(-1)).alias("a"), F.col("role").alias("b")))
    first, steps = np.full(3, 0.5), np.full((3, 3), 0.5)
    for a, b, n in pairs.groupBy("a", "b").agg(F.count("*").alias("n")).collect():  # at most twelve rows
        if a < 0:
            first[b] += n
        else:
            steps[a, b] += n
    return first / first.sum(), steps / steps.sum(1, keepdims=True)


def train(lines: DataFrame) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Log probabilities of the first state, of steps between states, and of symbols by state, from counts over all
    labelled lines given."""
    counts = np.ones((6, SYMBOLS)) * 0.1
    for r in lines.where("true_state is not null").groupBy("true_state", "symbol").agg(F.count("*").alias("n")).collect():
        counts[r[0], r[1]] += r[2]
    total = counts.sum(1)
    starts, follows = role_steps(lines)
    step = np.zeros((6, 6))
    for a in range(3):
        goes_on = total[2 * a + 1] / (total[2 * a] + total[2 * a + 1])
        step[[2 * a, 2 * a + 1], 2 * a + 1] = goes_on
        for b in range(3):
            step[[2 * a, 2 * a + 1], 2 * b] = (1 - goes_on) * follows[a, b]
    first = np.zeros(6)
    first[::2] = starts
    with np.errstate(divide="ignore"):
        return np.log(first), np.log(step), np.log(counts / total[:, None])


def _runs(batches: Iterator[pa.RecordBatch]):
    """(key, rows) of each chunk; rows come sorted by chunk."""
    key, held = None, []
    for batch in batches:
        for row in batch.to_pylist():
            k = row["conv_id"], row["chunk"]
            if k != key and held:
                yield key, held
                held = []
            key = k
            held.append(row)
    if held:
        yield key, held


def _paths(step: np.ndarray, emit: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Best scores at the end for each row of ``start`` (scores of the first line's states without its emission)."""
    score = start + emit[0]
    for e in emit[1:]:
        score = (score[:, :, None] + step[None]).max(1) + e
    return score


def _viterbi(step: np.ndarray, emit: np.ndarray, start: np.ndarray, last: int | None) -> list[int]:
    score, back = start + emit[0], []
    for e in emit[1:]:
        ways = score[:, None] + step
        back.append(ways.argmax(0).astype(np.int8))
        score = ways.max(0) + e
    state = int(score.argmax()) if last is None else last
    path = [state]
    for b in reversed(back):
        path.append(int(b[path[-1]]))
    return path[::-1]


def decode(lines: DataFrame, model: tuple[np.ndarray, np.ndarray, np.ndarray], chunk_turns: int = CHUNK) -> DataFrame:
    """Per line: conv_id, chunk, turn, tie, line_no, line, state, true_state."""
    held = lines.sparkSession.sparkContext.broadcast(model)
    order = ["conv_id", "chunk", "turn", "tie", "line_no"]
    lines = chunked(lines, chunk_turns)
    kind = lines.schema["conv_id"].dataType.simpleString()
    turn_kind = lines.schema["turn"].dataType.simpleString()
    chunks = lines.groupBy("conv_id").agg(F.min("chunk").alias("first"), F.max("chunk").alias("last"))
    long_ones = cut(chunks.where("first < last").select(F.col("conv_id").alias("c")))

    def matrices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first, step, emit = held.value
        for (conv, chunk), rows in _runs(batches):
            seen = emit[:, [r["symbol"] for r in rows]].T
            inside = _paths(step, seen, step)
            outset = _paths(step, seen, first[None])
            yield pa.RecordBatch.from_arrays([pa.array([conv], batch_kind), pa.array([chunk], pa.int64()), pa.array([np.vstack([inside, outset]).ravel()], pa.list_(pa.float64()))], ["conv_id", "chunk", "m"])

    batch_kind, turn_batch_kind = (to_arrow_type(lines.schema[c].dataType) for c in ("conv_id", "turn"))

    def ends(pdf: pd.DataFrame) -> pd.DataFrame:
        """States before and at the end of each chunk of one long conversation, along its best path."""
        pdf = pdf.sort_values("chunk").reset_index(drop=True)
        maps = [np.array(m).reshape(7, 6) for m in pdf["m"]]
        score, back = maps[0][6], []
        for m in maps[1:]:
            ways = score[:, None] + m[:6]
            back.append(ways.argmax(0))
            score = ways.max(0)
        path = [int(score.argmax())]
        for b in reversed(back):
            path.append(int(b[path[-1]]))
        path = path[::-1]
        return pdf[["conv_id", "chunk"]].assign(before=[-1, *path[:-1]], last=path)

    some = lines.join(long_ones, F.col("conv_id").eqNullSafe(F.col("c")), "left_semi").select("conv_id", "chunk", "turn", "tie", "line_no", "symbol")
    maps = some.repartition("conv_id", "chunk").sortWithinPartitions(*order).select("conv_id", "chunk", "symbol").mapInArrow(lean(matrices), f"conv_id {kind}, chunk bigint, m array<double>")
    bounds = cut(maps.groupBy("conv_id").applyInPandas(ends, f"conv_id {kind}, chunk bigint, before int, last int"))
    bounds = bounds.select(F.col("conv_id").alias("_c"), F.col("chunk").alias("_k"), "before", "last")

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first, step, emit = held.value
        kinds = [("conv_id", batch_kind), ("chunk", pa.int64()), ("turn", turn_batch_kind), ("tie", pa.int64()), ("line_no", pa.int32()), ("line", pa.string()), ("state", pa.int32()), ("true_state", pa.int32())]
        names = [n for n, _ in kinds]
        for _, rows in _runs(batches):
            seen = emit[:, [r["symbol"] for r in rows]].T
            before, last = rows[0]["before"], rows[0]["last"]
            path = _viterbi(step, seen, first if before is None or before < 0 else step[before], last)
            for r, s in zip(rows, path):
                r["state"] = s
            yield pa.RecordBatch.from_pylist([{n: r[n] for n in names} for r in rows], schema=pa.schema(kinds))

    both = lines.join(bounds, F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("chunk") == F.col("_k")), "left")
    dealt = both.select("conv_id", "chunk", "turn", "tie", "line_no", "line", "symbol", "true_state", "before", "last").repartition("conv_id", "chunk").sortWithinPartitions(*order)
    return dealt.mapInArrow(lean(best), f"conv_id {kind}, chunk bigint, turn {turn_kind}, tie bigint, line_no int, line string, state int, true_state int")


def strip_marker(line: Column) -> Column:
    out = line
    for style in STYLES:
        for mark in style.values():
            out = F.when(line.startswith(mark), F.expr(f"substring(line, {len(mark) + 1})")).otherwise(out)
    return out


def render(decoded: DataFrame) -> DataFrame:
    """Canonical turns: conv_id, seq (from 1), role, content, rendered.

    Lines are in order by (turn, tie, line_no); a line whose state begins a turn opens the next one. Turns are numbered
    within chunks and, by a row per chunk, over them, so a turn may go on over a chunk's border.
    """
    order = Window.partitionBy("conv_id", "chunk").orderBy("turn", "tie", "line_no")
    opened = decoded.withColumn("opens", (F.pmod("state", F.lit(2)) == 0).cast("int"))
    chunks = opened.groupBy("conv_id", "chunk").agg(F.sum("opens").alias("opened"))
    earlier = Window.partitionBy("conv_id").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    base = chunks.select(F.col("conv_id").alias("_c"), F.col("chunk").alias("_k"), F.coalesce(F.sum("opened").over(earlier), F.lit(0)).alias("base"))
    numbered = opened.withColumn("at", F.row_number().over(order)).withColumn("local", F.sum("opens").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    numbered = numbered.join(base, F.col("conv_id").eqNullSafe(F.col("_c")) & (F.col("chunk") == F.col("_k")))
    role = F.element_at(F.lit(ROLES), F.floor(F.col("state") / 2).cast("int") + 1)
    lines = numbered.select("conv_id", (F.col("base") + F.col("local")).alias("seq"), F.struct("chunk", "at").alias("place"), role.alias("role"), strip_marker(F.col("line")).alias("clean"))
    turns = lines.groupBy("conv_id", "seq").agg(
        F.min_by("role", "place").alias("role"), F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("place", "clean"))), lambda x: x["clean"]), "\n").alias("content")
    )
    text = F.concat(F.lit("<|start|>"), F.col("role"), F.lit("\n"), F.col("content"), F.lit("<|end|>\n"))
    return turns.select("conv_id", "seq", "role", "content", text.alias("rendered"))
