"""Chat formatting: roles of transcript lines by a hidden Markov model.

A transcript comes in rows (id, pos, text) of one or more lines; some lines start
with a speaker's marker. States of the model are the three roles, each as first or
later line of a turn, and one state before the first line. Lines are observed as
marker, shape and length. Transitions and emissions are counted on labelled turns,
over all of them, and kept as whole numbers (rounded log-probabilities), so a sum of
scores does not depend on the order of summing.

Decoding is exact for transcripts of any length. Rows are cut into blocks of
``FAN`` positions; a block is the max-plus product of its lines' matrices; blocks are
multiplied in blocks of ``FAN`` again until each transcript is one sequence of at most
``FAN``, whose best states fix the ends of the blocks below, and so on down to the
lines. No task holds more than a block, however long one conversation is.

Rendering opens each turn with its role's tag on a line of its own and drops the
marker; the rows of a transcript, one after the other, are its canonical form.

The query decodes each transcript with a model that was fitted on others: transcripts
fall into two folds by a hash of the id, and each fold is decoded by the other's model.

Nulls: a null text is one blank line; a row without an id is a transcript of its own; rows
without a position come first, in the order of a hash of the text, which spreads them over
blocks. Rows equal in id, position and text are one row of the transcript, and each gets
its result; texts that share id and position are ordered by a hash of the text and meet in
one block. Positions are above -2^61. A very long text is decoded by the task that holds
its block. An empty table gives an empty result. Further columns are dropped.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise

ROLES = ["system", "user", "assistant"]
STATES = 7  # first lines of the roles, later lines of the roles, before all lines
BEGIN = 6
FAN = 64
SCALE = 1000
NEVER = -(10**9)
# speakers' markers.
MARKERS = {"user": ["User", "Human", "Q"], "assistant": ["Assistant", "AI", "A"], "system": ["System"]}
MARKER = {r: rf"^\s*({'|'.join(m)})\s*:\s?" for r, m in MARKERS.items()}
ANY_MARKER = r"^\s*[A-Z][A-Za-z]{0,19}\s*:\s"
OBSERVATIONS = 60


def observation(line: Column) -> Column:
    """0 to 59 from the line's marker (none, system, user, assistant, other), shape (blank, question, list or code, other) and length."""
    marker = F.when(F.regexp_like(line, F.lit(MARKER["system"])), 1).when(F.regexp_like(line, F.lit(MARKER["user"])), 2)
    marker = marker.when(F.regexp_like(line, F.lit(MARKER["assistant"])), 3).when(F.regexp_like(line, F.lit(ANY_MARKER)), 4).otherwise(0)
    shape = F.when(F.regexp_like(line, F.lit(r"^\s*$")), 0).when(F.regexp_like(line, F.lit(r"\?\s*$")), 1).when(F.regexp_like(line, F.lit(r"^\s*([-*#`]|\d+[.)])")), 2).otherwise(3)
    length = F.when(F.length(line) < 80, 0).when(F.length(line) < 300, 1).otherwise(2)
    return (marker * 4 + shape) * 3 + length


def observed(rows: DataFrame) -> DataFrame:
    """Adds ``obs``, the observations of the text's lines."""
    lines = F.split(F.coalesce("text", F.lit("")), "\n")
    return rows.withColumn("obs", F.transform(lines, observation))


class Model:
    """Whole-number log-probabilities: ``step[a, b]`` and ``emit[state, observation]``."""

    def __init__(self, step: np.ndarray, emit: np.ndarray):
        self.step, self.emit = step, emit

    def line(self, obs: int) -> np.ndarray:
        out = self.step + self.emit[:, obs][None, :]
        out[:, BEGIN] = NEVER
        return out


def fit(turns: DataFrame) -> Model:
    """Counts over all labelled rows (id, pos, role, text); a turn's successor is the row at the next position."""
    seen = observed(turns.where(F.col("role").isin(ROLES)).select("id", "pos", "role", "text"))
    of = F.array_position(F.array(*map(F.lit, ROLES)), F.col("role")).cast("int") - 1
    seen = seen.select("id", "pos", of.alias("r"), "obs")
    lines = seen.select("r", F.posexplode("obs").alias("k", "o"))
    emits = lines.groupBy((F.col("r") + F.when(F.col("k") > 0, 3).otherwise(0)).alias("s"), "o").count().collect()  # at most 360 rows
    size = F.size("obs")
    inner = seen.groupBy("r").agg(F.sum((size > 1).cast("long")).alias("a"), F.sum(F.greatest(size - 2, F.lit(0))).alias("b"), F.count("*").alias("n")).collect()
    after = seen.select(F.col("id").alias("i"), (F.col("pos") - 1).alias("p"), F.col("r").alias("next"))
    pairs = seen.join(after, F.col("id").eqNullSafe(F.col("i")) & (F.col("pos") == F.col("p")))
    moves = pairs.groupBy("r", (size > 1).alias("long"), "next").count().collect()
    firsts = seen.groupBy("id").agg(F.min_by("r", "pos").alias("r")).groupBy("r").count().collect()
    step, emit = np.full((STATES, STATES), 0.0), np.full((STATES, OBSERVATIONS), 0.01)
    step[:, :3] = 0.01
    for r in range(3):
        step[r, r + 3] = step[r + 3, r + 3] = 0.01
    for x in emits:
        emit[x["s"], x["o"]] += x["count"]
    for x in inner:
        step[x["r"], x["r"] + 3] += x["a"]
        step[x["r"] + 3, x["r"] + 3] += x["b"]
    for x in moves:
        step[x["r"] + 3 * x["long"], x["next"]] += x["count"]
    for x in firsts:
        step[BEGIN, x["r"]] += x["count"]
    with np.errstate(divide="ignore"):
        logs = [np.log(m / m.sum(axis=1, keepdims=True)) for m in (step, emit)]
    step, emit = [np.where(np.isfinite(x), np.rint(SCALE * np.maximum(x, NEVER)), NEVER).astype(np.int64) for x in logs]
    return Model(step, emit)


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Max-plus product."""
    return np.maximum((a[:, :, None] + b[None, :, :]).max(axis=1), NEVER)


def best_states(matrices: list[np.ndarray], start: int, end: int) -> list[int]:
    """States after each matrix on a best way from ``start`` to ``end`` (-1: any end); the least state on ties."""
    score, back = np.full(STATES, NEVER, dtype=np.int64), []
    score[start] = 0
    for m in matrices:
        way = score[:, None] + m
        back.append(way.argmax(axis=0))
        score = np.maximum(way.max(axis=0), NEVER)
    state = int(score.argmax()) if end < 0 else end
    out = [state]
    for k in range(len(matrices) - 1, 0, -1):
        state = int(back[k][state])
        out.append(state)
    return out[::-1]


def _grouped(df: DataFrame, keys: list[str], order: list[Column], body: Callable[[list[dict]], list[dict]], schema: str) -> DataFrame:
    """``body`` on the rows of each group, which are at most a block, in order."""
    group = F.xxhash64(*keys)
    dealt = df.withColumn("__g", group).repartition("__g").sortWithinPartitions(*keys, *order)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest: list[dict] = []
        for batch in batches:
            for start in range(0, batch.num_rows, 2048):
                rows, done = rest + batch.slice(start, 2048).to_pylist(), []
                cut = 0
                for k in range(1, len(rows)):
                    if any(rows[k][x] != rows[cut][x] for x in keys):
                        done += body(rows[cut:k])
                        cut = k
                rest = rows[cut:]
                if done:
                    yield pa.RecordBatch.from_pylist(done, schema=arrow)
        if rest:
            yield pa.RecordBatch.from_pylist(body(rest), schema=arrow)

    arrow = _arrow_schema(schema)
    return dealt.drop("__g").mapInArrow(run, schema)


def _arrow_schema(schema: str) -> pa.Schema:
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string(), "array<bigint>": pa.list_(pa.int64()), "array<int>": pa.list_(pa.int32())}
    return pa.schema([(name, kinds[kind]) for name, kind in (part.strip().split(" ") for part in schema.split(","))])


def decode_rows(rows: DataFrame, model: Model, fan: int = FAN) -> DataFrame:
    """(id, pos, tie, text, states array<int>): the state of each line of each row."""
    spark = rows.sparkSession
    of = spark.sparkContext.broadcast(model)
    tie = F.xxhash64("text")
    own = rows.select(F.col("id").cast("bigint").alias("id"), F.col("pos").cast("bigint").alias("pos"), "text").groupBy("id", "pos", "text").agg(F.count("*").alias("copies"))
    lost = F.concat_ws(":", F.lit("x"), tie, F.xxhash64(F.lit("lost"), "text", "pos"))
    own = own.select(
        F.when(F.col("id").isNull(), lost).otherwise(F.concat(F.lit("i"), "id")).alias("id"),
        F.coalesce("pos", F.shiftrightunsigned(tie, 24) - F.lit(1 << 62)).alias("pos"),
        "text", tie.alias("tie"), "copies",
    )
    block = F.expr(f"pos div {fan}") - F.expr(f"int(pos < 0 and pos % {fan} <> 0)")  # rounds down; no doubles, which lose digits
    seen = observed(own).withColumn("block", block)
    flat = lambda m: m.reshape(-1).tolist()

    def of_lines(group: list[dict]) -> list[dict]:
        total = None
        for row in group:
            for o in row["obs"]:
                m = of.value.line(o)
                total = m if total is None else times(total, m)
        return [{"id": group[0]["id"], "pos": group[0]["block"], "m": flat(total)}]

    def of_blocks(group: list[dict]) -> list[dict]:
        total = None
        for row in group:
            m = np.array(row["m"]).reshape(STATES, STATES)
            total = m if total is None else times(total, m)
        return [{"id": group[0]["id"], "pos": group[0]["block"], "m": flat(total)}]

    def ends(group: list[dict]) -> list[dict]:
        start, end = group[0].get("s", BEGIN), group[0].get("e", -1)
        states = best_states([np.array(r["m"]).reshape(STATES, STATES) for r in group], start, end)
        return [{"id": r["id"], "pos": r["pos"], "s": a, "e": b} for r, a, b in zip(group, [start, *states], states, strict=False)]

    def lines(group: list[dict]) -> list[dict]:
        matrices = [of.value.line(o) for r in group for o in r["obs"]]
        states, out = best_states(matrices, group[0]["s"], group[0]["e"]), []
        for r in group:
            out.append({k: r[k] for k in ("id", "pos", "tie", "text", "copies")} | {"states": states[: len(r["obs"])]})
            states = states[len(r["obs"]) :]
        return out

    matrix, between = "id string, pos bigint, m array<bigint>", "id string, pos bigint, s int, e int"
    levels = [materialise(_grouped(seen.select("id", "pos", "tie", "block", "obs"), ["id", "block"], ["pos", "tie"], of_lines, matrix), "chat-blocks")]
    while (levels[-1].groupBy("id").count().agg(F.max("count")).first()[0] or 0) > fan:
        up = levels[-1].withColumn("block", block)
        levels.append(materialise(_grouped(up, ["id", "block"], ["pos"], of_blocks, matrix), "chat-blocks"))
    fixed = _grouped(levels[-1], ["id"], ["pos"], ends, between)
    same = lambda a, b: F.col(a).eqNullSafe(F.col(b))
    for level in levels[-2::-1]:
        above = fixed.select(F.col("id").alias("i"), F.col("pos").alias("p"), "s", "e")
        down = level.withColumn("block", block).join(above, same("id", "i") & (F.col("block") == F.col("p")))
        fixed = _grouped(down.drop("i", "p"), ["id", "block"], ["pos"], ends, between)
    above = fixed.select(F.col("id").alias("i"), F.col("pos").alias("p"), "s", "e")
    down = seen.join(above, same("id", "i") & (F.col("block") == F.col("p"))).drop("i", "p")
    out = _grouped(down, ["id", "block"], ["pos", "tie"], lines, "id string, pos bigint, tie bigint, text string, copies bigint, states array<int>")
    out = out.withColumn("copies", F.explode(F.sequence(F.lit(1).cast("bigint"), "copies")))
    return out.select(
        F.when(F.col("id").startswith("i"), F.expr("substring(id, 2)").cast("bigint")).alias("id"),
        F.when(F.col("pos") > -(1 << 61), F.col("pos")).alias("pos"), "tie", "text", "states",
    )


def rendered(text: Column, states: Column) -> Column:
    """The row's lines with a tag before each line that opens a turn."""
    lines = F.split(F.coalesce(text, F.lit("")), "\n")
    any_of = "|".join(m for ms in MARKERS.values() for m in ms)
    tag = lambda s: F.element_at(F.array(*map(F.lit, ROLES)), s + 1)
    opened = lambda x, s: F.concat(F.lit("<|"), tag(s), F.lit("|>\n"), F.regexp_replace(x, rf"^\s*({any_of})\s*:\s?", ""))
    return F.array_join(F.zip_with(lines, states, lambda x, s: F.when(s < 3, opened(x, F.least(s, F.lit(2)))).otherwise(x)), "\n")


def format_transcripts(rows: DataFrame, model: Model, fan: int = FAN) -> DataFrame:
    """(id, pos, role, n_turns, rendered): the role of the row's first line, turns that open in the row, canonical text."""
    decoded = decode_rows(rows, model, fan)
    first = F.element_at("states", 1) % 3
    return decoded.select(
        "id", "pos",
        F.element_at(F.array(*map(F.lit, ROLES)), first + 1).alias("role"),
        F.size(F.filter("states", lambda s: s < 3)).cast("long").alias("n_turns"),
        rendered(F.col("text"), F.col("states")).alias("rendered"),
    )


def as_transcript(turns: DataFrame, drop_every: int = 4) -> DataFrame:
    """(id, pos, role, text) of ``conversations``: markers before the turns, in varying form; one turn in ``drop_every`` has none."""
    pick = F.pmod(F.xxhash64("conv_id", "turn"), F.lit(12))
    forms = [F.element_at(F.array(*map(F.lit, MARKERS[r])), (F.pmod(pick, F.lit(len(MARKERS[r]))) + 1).cast("int")) for r in ROLES]
    marker = F.when(F.col("role") == ROLES[0], forms[0]).when(F.col("role") == ROLES[1], forms[1]).when(F.col("role") == ROLES[2], forms[2])
    named = (F.pmod(F.xxhash64("turn", "conv_id"), F.lit(drop_every)) > 0) & marker.isNotNull()
    text = F.coalesce("text", F.lit(""))
    return turns.select(F.col("conv_id").alias("id"), F.col("turn").cast("bigint").alias("pos"), "role", F.when(named, F.concat(marker, F.lit(": "), text)).otherwise(text).alias("text"))


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recovered role and canonical text of every row of the transcripts of ``conversations``, by models that have not seen them."""
    transcripts = as_transcript(spark.read.parquet(f"{sf_dir}/conversations.parquet"))
    fold, out = F.pmod(F.xxhash64("id"), F.lit(2)), None
    for k in (0, 1):
        held = format_transcripts(transcripts.where(fold == k).select("id", "pos", "text"), fit(transcripts.where(fold != k)))
        out = held if out is None else out.unionByName(held)
    return out.select(F.col("id").alias("conv_id"), F.col("pos").alias("turn"), "role", "n_turns", "rendered")
