"""Chat transcripts: roles recovered by a hidden Markov model over lines, then one canonical rendering.

Each line of a transcript has features: the kind of speaker marker it begins with, whether it or the line before is blank,
its length, whether it asks. Hidden states say which role speaks and whether the line opens a turn. Start, move and
feature probabilities are counted on a bounded sample of transcripts with known roles; Viterbi finds the likeliest
states of a whole transcript, so lines without markers get their role from what stands around them.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from certgraph.plans.staging import Stages

ROLES = ("system", "user", "assistant")
#: Labelled conversations that the model is fitted on, and turns of one conversation that make one transcript at most.
FIT_CONVERSATIONS, SEGMENT_TURNS = 500, 1024
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"

# Speaker names by role, and how each style of transcript writes them.
_NAMES = {
    "system": ("system", "instructions", "context"),
    "user": ("user", "human", "q", "question", "customer", "me", "instruction", "prompt"),
    "assistant": ("assistant", "ai", "a", "answer", "bot", "agent", "response", "model"),
}
_ROLE_OF = {n: r for r, names in _NAMES.items() for n in names}
_MARKER = re.compile(r"^\s*(?:<\|(?:im_start\|>)?\s*(?P<tag>[A-Za-z]{1,20})(?:\|>)?|\[(?P<square>[A-Za-z]{1,20})\]|#{2,4}\s*(?P<head>[A-Za-z]{1,20})\s*:?|\*{0,2}(?P<name>[A-Za-z]{1,20})\*{0,2}\s*:)\*{0,2}\s*", re.ASCII)
_KINDS = ("none", "other", *ROLES)
_LENGTHS = (0, 40, 120, 400)
_SIZES = (len(_KINDS), 2, 2, len(_LENGTHS) + 1, 2)  # marker, blank, blank before, length, asks
STATES = tuple((r, k) for r in range(len(ROLES)) for k in (0, 1))  # role, 0 opens a turn and 1 goes on


def _marker(line: str) -> tuple[int, int]:
    """Kind of speaker marker, and where the line's own text begins."""
    m = _MARKER.match(line)
    if not m:
        return 0, 0
    name = next(g for g in m.groups() if g).lower()
    role = _ROLE_OF.get(name)
    return (2 + ROLES.index(role), m.end()) if role else (1, 0)


def line_features(lines: list[str]) -> tuple[np.ndarray, list[int]]:
    rows, begins, before = np.zeros((len(lines), len(_SIZES)), dtype=np.int64), [], 1
    for i, line in enumerate(lines):
        kind, at = _marker(line)
        blank = int(not line.strip())
        rows[i] = kind, blank, before, sum(len(line) > n for n in _LENGTHS), int(line.rstrip().endswith("?"))
        before = blank
        begins.append(at)
    return rows, begins


class TranscriptModel:
    """Log probabilities of first states, moves and each feature."""

    def __init__(self, first: np.ndarray, move: np.ndarray, features: list[np.ndarray]):
        self.first, self.move, self.features = first, move, features

    @staticmethod
    def fitted(labelled: list[tuple[list[str], list[int]]]) -> TranscriptModel:
        """From lines with their states."""
        n = len(STATES)
        first, move, features = np.full(n, 0.5), np.full((n, n), 0.1), [np.full((n, k), 0.1) for k in _SIZES]
        first[[i for i, (_, k) in enumerate(STATES) if k]] = 1e-6
        for lines, states in labelled:
            if not lines:
                continue
            rows, _ = line_features(lines)
            first[states[0]] += 1
            np.add.at(move, (states[:-1], states[1:]), 1)
            for j, f in enumerate(features):
                np.add.at(f, (states, rows[:, j]), 1)
        for i, (r, _) in enumerate(STATES):  # only the same role goes on
            for j, (q, k) in enumerate(STATES):
                if k and q != r:
                    move[i, j] = 1e-9
        logs = [np.log(x / x.sum(axis=-1, keepdims=True)) for x in (first, move, *features)]
        return TranscriptModel(logs[0], logs[1], logs[2:])

    def states(self, lines: list[str]) -> tuple[np.ndarray, list[int]]:
        """Likeliest state of each line."""
        rows, begins = line_features(lines)
        seen = sum(f[:, rows[:, j]] for j, f in enumerate(self.features)).T
        back = np.zeros((len(lines), len(STATES)), dtype=np.int64)
        best = self.first + seen[0]
        for i in range(1, len(lines)):
            via = best[:, None] + self.move
            back[i] = via.argmax(axis=0)
            best = via[back[i], np.arange(len(STATES))] + seen[i]
        path = np.zeros(len(lines), dtype=np.int64)
        path[-1] = best.argmax()
        for i in range(len(lines) - 1, 0, -1):
            path[i - 1] = back[i, path[i]]
        return path, begins

    def turns(self, text: str | None) -> list[tuple[str, str]]:
        """(role, text) of each turn; a text without any line that isn't blank has none."""
        if not text or not text.strip():
            return []
        lines = text.split("\n")
        path, begins = self.states(lines)
        out: list[tuple[str, list[str]]] = []
        for line, s, at in zip(lines, path, begins, strict=True):
            role, goes_on = STATES[s]
            if not out or not goes_on:
                out.append((ROLES[role], [line[at:]]))
            else:
                out[-1][1].append(line)
        return [(r, "\n".join(x).strip()) for r, x in out]


def render_turns(turns: list[tuple[str, str]]) -> str:
    """Canonical form: each turn between the two marks, its role on the first line."""
    return "".join(f"{OPEN}{role}\n{text}{CLOSE}\n" for role, text in turns)


def _write_turn(role: str, text: str, style: int, marked: bool) -> str:
    name = _NAMES[role][style % 2]
    mark = (f"{name.capitalize()}: ", f"{name.upper() if len(name) < 3 else name.capitalize()}: ", f"<|{role}|>\n", f"[{role.upper()}] ", f"### {name.capitalize()}:\n", f"**{role.capitalize()}**: ")[style]
    return (mark if marked else "") + text


def _joined(roles: list[str], texts: list[str], style: int) -> tuple[str, list[int]]:
    """A transcript in a style, and the state of each of its lines. Styles above five leave out later markers and part turns by blank lines."""
    lines: list[str] = []
    states: list[int] = []
    for i, (role, text) in enumerate(zip(roles, texts, strict=True)):
        if i and (style % 2 == 0 or style > 5):
            lines.append("")
            states.append(states[-1] | 1)
        r = ROLES.index(role)
        own = _write_turn(role, text, style % 6, style < 6 or i < 2).split("\n")
        lines += own
        states += [2 * r] + [2 * r + 1] * (len(own) - 1)
    return "\n".join(lines), states


_TRANSCRIPT_DDL = "conv_id long, segment long, n_turns int, roles array<string>, transcript string, states array<int>"


def _assembled(table: pa.Table) -> pa.Table:
    rows = sorted(table.to_pylist(), key=lambda r: (r["turn"] is None, r["turn"] or 0, r["text"], r["role"]))
    roles, texts = [r["role"] if r["role"] in ROLES else "user" for r in rows], [r["text"] for r in rows]
    text, states = _joined(roles, texts, rows[0]["style"])
    one = {"conv_id": rows[0]["conv_id"], "segment": rows[0]["segment"], "n_turns": len(rows), "roles": roles, "transcript": text, "states": states}
    return pa.Table.from_pylist([one], schema=pa.schema([("conv_id", pa.int64()), ("segment", pa.int64()), ("n_turns", pa.int32()), ("roles", pa.list_(pa.string())), ("transcript", pa.string()), ("states", pa.list_(pa.int32()))]))


def as_transcripts(conversations: DataFrame) -> DataFrame:
    """Plain transcripts of conversations (conv_id, turn, role, text), in one of eight styles by conv_id.

    A transcript holds at most about SEGMENT_TURNS turns, so that a conversation of any length is never gathered in one
    task: longer ones are cut by turn number, and turns that repeat a number are split by a hash and, where rows are
    equal, by how many there are. Rows without conv_id are transcripts of their own; a null text is empty; a role that isn't known
    counts as user.
    """
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    h = F.xxhash64("turn", "role", "text")
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), text.alias("text"))
    rows = rows.withColumn("own", F.when(F.col("conv_id").isNull(), h).otherwise(F.lit(0))).withColumn("cut", F.coalesce(F.floor(F.col("turn") / SEGMENT_TURNS), F.lit(0)))
    many = rows.groupBy("conv_id", "own", "cut").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > SEGMENT_TURNS)
    many = many.select(F.col("conv_id").alias("k"), F.col("own").alias("o"), F.col("cut").alias("c"), F.ceil(F.col("n") / SEGMENT_TURNS).alias("pieces"))
    rows = rows.join(many, F.col("conv_id").eqNullSafe(F.col("k")) & (F.col("own") == F.col("o")) & (F.col("cut") == F.col("c")), "left").drop("k", "o", "c")
    few = rows.filter("pieces IS NULL").withColumn("piece", F.lit(0).cast("long")).drop("pieces")
    equal = rows.filter("pieces IS NOT NULL").groupBy("conv_id", "turn", "role", "text", "own", "cut", "pieces").agg(F.count(F.lit(1)).alias("n"))
    spread = equal.withColumn("nth", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1))).withColumn("piece", F.pmod(F.pmod(F.xxhash64("text", "role"), F.col("pieces")) + F.col("nth"), F.col("pieces")))
    rows = few.unionByName(spread.drop("n", "nth", "pieces"))
    rows = rows.withColumn("segment", F.col("cut") * 1_000_000 + F.col("piece")).withColumn("style", F.pmod(F.xxhash64("conv_id", "segment"), F.lit(8)).cast("int"))
    return rows.select("conv_id", "own", "segment", "turn", "role", "text", "style").groupBy("conv_id", "own", "segment").applyInArrow(_assembled, _TRANSCRIPT_DDL)


def fitted_model(transcripts: DataFrame) -> TranscriptModel:
    """From FIT_CONVERSATIONS labelled transcripts, chosen by hash."""
    rows = transcripts.orderBy(F.xxhash64("conv_id", "segment")).limit(FIT_CONVERSATIONS).select("transcript", "states").collect()
    return TranscriptModel.fitted([(r.transcript.split("\n"), list(r.states)) for r in rows if r.states])


def parse_transcripts(transcripts: DataFrame, model: TranscriptModel, text_col: str = "transcript") -> DataFrame:
    """Adds `turns` (role, text) and the canonical `chat` to each transcript; a null or blank one has no turns.

    Other columns stay, whatever their names; columns that are called turns or chat already are replaced.
    """
    shared = transcripts.sparkSession.sparkContext.broadcast(model)
    rest = [c for c in transcripts.columns if c.lower() not in ("turns", "chat") or c.lower() == text_col.lower()]
    at = [c.lower() for c in rest].index(text_col.lower())
    names = [f"c{i}" for i in range(len(rest))]
    plain = transcripts.select(*(F.col(f"`{c.replace('`', '``')}`").alias(n) for c, n in zip(rest, names, strict=True)))
    added = T.ArrayType(T.StructType([T.StructField("role", T.StringType()), T.StructField("text", T.StringType())]))
    schema = T.StructType([*plain.schema.fields, T.StructField("turns", added), T.StructField("chat", T.StringType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("role", pa.string()), ("text", pa.string())]))
        for batch in batches:
            turns = [shared.value.turns(t) for t in batch.column(at).to_pylist()]
            own = [[{"role": r, "text": x} for r, x in t] for t in turns]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(own, kind), pa.array([render_turns(t) for t in turns], pa.string())], names=[*batch.schema.names, "turns", "chat"])

    return plain.mapInArrow(run, schema).toDF(*rest, "turns", "chat")


def formatted_chats(conversations: DataFrame) -> DataFrame:
    """conv_id, segment, n_turns, n_found, roles_right, chat: transcripts of the conversations, parsed and rendered.

    roles_right counts the turns whose role and place were recovered, all of them or, if another number was found, those
    up to the first difference. An empty table gives an empty result.
    """
    st = Stages(conversations.sparkSession, "chat")
    transcripts = st.keep(as_transcripts(conversations), "transcripts")
    parsed = parse_transcripts(transcripts.select("conv_id", "segment", "n_turns", "roles", "transcript"), fitted_model(transcripts))
    found = F.col("turns.role")
    same = F.expr("aggregate(zip_with(roles, turns.role, (a, b) -> a <=> b), named_struct('n', 0, 'on', true), (s, x) -> named_struct('n', s.n + if(s.on and x, 1, 0), 'on', s.on and x), s -> s.n)")
    return parsed.select("conv_id", "segment", "n_turns", F.size(found).alias("n_found"), same.alias("roles_right"), "chat")
