"""Chat formatting: roles of transcript blocks by a hidden Markov model, then canonical turns.

A transcript is a sequence of blocks (turns of a table, or the parts of a raw text between speaker
markers and blank lines). The hidden state of a block is its role; what is observed are the
speaker marker that its first line begins with, if any, and features of its lines: how long the
block is, how many lines it has, how its first line begins and its last line ends. Start,
transition and emission probabilities are smoothed counts over labelled blocks; a marker that
names a speaker also has a fixed prior, so that it decides where no labelled block had markers.
Viterbi gives the most likely roles of the whole transcript.

Rendering strips the marker and writes every turn as the role's opening, the text and the closing.

Transcripts are sorted within partitions and streamed. A block's role is decided as soon as the best paths to all
states of a later block agree on it, which leaves the path that a search over the whole transcript finds; memory
holds the blocks that are not decided yet. Blocks without an id are dealt out by their text.

Defined cases: null and empty texts are blocks of no lines and get a role like any other; turns that
repeat keep the order of turn, then text; every row with a null id is a transcript of its own; null turns come
first; a very long text is one block, a very long transcript is decided in parts as above; an empty table gives no
rows; unknown or null roles are not learnt from; without labelled blocks the model knows markers and
alternation only; further columns are ignored, whatever their names.
"""

from __future__ import annotations

import math
import re
from collections import Counter, deque
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batched, is_trained_on, prepare, rows_of
from .decontaminate import _arrow

ROLES = ("system", "user", "assistant")
DIVISOR, HELD_OUT = 5, 0
#: Blocks after which paths are looked at for what they agree on.
SETTLE = 1 << 10
#: Speaker names by role, as they begin a block.
SPEAKERS = {
    "system": ["system", "system prompt", "instructions"],
    "user": ["user", "human", "you", "customer", "client", "question", "q", "me", "student", "prompt"],
    "assistant": ["assistant", "ai", "bot", "chatbot", "agent", "support", "answer", "a", "response", "model", "teacher"],
}
_ROLE_OF = {name: role for role, names in SPEAKERS.items() for name in names}
_NAMES = "|".join(sorted(map(re.escape, _ROLE_OF), key=len, reverse=True))
MARKER = re.compile(rf"\s*(?:(?:#+|\*+|>+|<\|?|\[|\()\s*)?({_NAMES})\s*(?:\|?>|\]|\)|\*+)?\s*(?::\*{{0,2}}|-(?= )|\|?>|\](?=\s|$)|(?<=>)|(?<=\])|$)\s*", re.IGNORECASE)
#: Probability that a marker speaks the truth.
TRUST = 0.98


def marker(text: str) -> tuple[str | None, int]:
    """The role that the first line's speaker marker names, and where the text behind it starts."""
    line = text.split("\n", 1)[0]
    found = MARKER.match(line)
    return (_ROLE_OF[found[1].lower()], found.end()) if found and found.end() else (None, 0)


def split_transcript(text: str | None) -> list[str]:
    """Blocks of a raw transcript: a marker or the line after a blank one begins one."""
    blocks: list[list[str]] = []
    fresh = True
    for line in (text or "").split("\n"):
        if not line.strip():
            fresh = True
            continue
        if marker(line)[0] or fresh or not blocks:
            blocks.append([])
        fresh = False
        blocks[-1].append(line)
    return ["\n".join(b) for b in blocks]


def features(text: str | None) -> tuple[str, ...]:
    """What is observed of a block besides its marker: one value for each feature."""
    body = text[marker(text)[1] :] if text else ""
    lines = [x for x in body.split("\n") if x.strip()]
    if not lines:
        return ("len=none", "lines=0", "first=none", "last=none", "words=0", "shape=none")
    n, words = len(body), len(body.split())
    first, last = lines[0].lstrip()[:1], lines[-1].rstrip()[-1:]
    kind = "upper" if first.isupper() else "lower" if first.islower() else "digit" if first.isdigit() else "mark"
    shape = "code" if "```" in body or "    " in body else "list" if any(x.lstrip()[:2] in ("- ", "* ", "1.") for x in lines) else "prose"
    return (f"len={n.bit_length() * 2 + (n >> max(0, n.bit_length() - 2) & 1)}", f"lines={min(len(lines), 8)}", f"first={kind}", f"last={last if last in '.?!:,' else 'other'}", f"words={words.bit_length()}", f"shape={shape}")


class RoleModel:
    """Log probabilities from counts: starts, transitions and emissions."""

    def __init__(self, counts: dict[tuple[str, str, str], int]):
        """counts: (kind, role, value) with kind ``start``, ``next`` (value: the next role) or ``see``."""
        r = range(len(ROLES))
        self.start = np.array([counts.get(("start", "", ROLES[k]), 0) + 0.5 for k in r])
        self.next = np.array([[counts.get(("next", ROLES[a], ROLES[b]), 0) + (0.05 if a == b else 0.5) for b in r] for a in r])
        self.start = np.log(self.start / self.start.sum())
        self.next = np.log(self.next / self.next.sum(1, keepdims=True))
        values: dict[str, set[str]] = {}
        for kind, _, value in counts:
            if kind == "see":
                values.setdefault(value.split("=")[0], set()).add(value)
        self.see: dict[str, np.ndarray] = {}
        self.unseen: dict[str, np.ndarray] = {}
        for name, some in values.items():
            totals = np.array([sum(counts.get(("see", role, v), 0) for v in some) for role in ROLES], float)
            size = 0.5 * (len(some) + 1)
            for v in some:
                own = np.array([counts.get(("see", role, v), 0) for role in ROLES], float)
                self.see[v] = np.log((own + 0.5) / (totals + size))
            self.unseen[name] = np.log(0.5 / (totals + size))

    def emission(self, text: str | None) -> np.ndarray:
        named = marker(text)[0] if text else None
        score = np.zeros(len(ROLES))
        if named:
            score += [math.log(TRUST if role == named else (1 - TRUST) / 2) for role in ROLES]
        # Features of one block say much the same: their sum counts half.
        for v in features(text):
            score += 0.5 * self.see.get(v, self.unseen.get(v.split("=")[0], np.zeros(len(ROLES))))
        return score

    def viterbi(self, emissions: Iterable[np.ndarray]) -> list[int]:
        """The most likely states."""
        path = Path(self)
        for e in emissions:
            path.add(e)
        return path.rest()


class Path:
    """Viterbi in one walk: back pointers of the steps that are not decided yet."""

    def __init__(self, model: RoleModel):
        self.model, self.score = model, None
        self.back: list[np.ndarray] = []

    def add(self, emission: np.ndarray) -> None:
        if self.score is None:
            self.score = self.model.start + emission
            self.back.append(np.arange(len(ROLES)))
            return
        step = self.score[:, None] + self.model.next
        self.back.append(step.argmax(0))
        best = step.max(0) + emission
        # Only differences matter; a long transcript's sums would lose them.
        self.score = best - best.max()

    def decided(self) -> list[int]:
        """States of the first steps that all paths have in common; these steps are let go."""
        states, agreed = np.arange(len(ROLES)), None
        for k in range(len(self.back) - 1, 0, -1):
            states = self.back[k][states]
            if (states == states[0]).all():
                agreed = k - 1
                break
        if agreed is None:
            return []
        path = self._trace(agreed, int(states[0]))
        # The step after the last decided one points back to it from every state that is still in question.
        self.back = self.back[agreed + 1 :]
        return path

    def rest(self) -> list[int]:
        if not self.back:
            return []
        return self._trace(len(self.back) - 1, int(self.score.argmax()))

    def _trace(self, last: int, state: int) -> list[int]:
        path = [state]
        for k in range(last, 0, -1):
            state = int(self.back[k][state])
            path.append(state)
        return path[::-1]


def render(role: str, text: str | None) -> str:
    """A canonical turn."""
    body = (text or "")[marker(text)[1] :] if text else ""
    return f"<|{role}|>\n{body.strip()}\n<|end|>\n"


def learn(turns: DataFrame) -> RoleModel:
    """Counts over all labelled rows: conv_id, turn, role, text."""
    prepare(turns.sparkSession)
    known = turns.where(F.col("role").isin(*ROLES)).select("conv_id", "turn", "role", "text")
    schema = pa.schema([("kind", pa.string()), ("role", pa.string()), ("value", pa.string()), ("n", pa.int64())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter = Counter()
        last: tuple = (object(), "")
        for conv_id, role, text in rows_of(batches, "conv_id", "role", "text"):
            goes_on = conv_id is not None and last[0] == conv_id
            found["next", last[1], role] += goes_on
            found["start", "", role] += not goes_on
            for v in features(text):
                found["see", role, v] += 1
            last = conv_id, role
        return batched(((*key, n) for key, n in found.items() if n), schema)

    ordered = _in_order(known)
    # Kinds, roles and feature values are few, whatever the number of rows.
    sums = ordered.mapInArrow(count, "kind string, role string, value string, n long").groupBy("kind", "role", "value").agg(F.sum("n").alias("n")).collect()
    return RoleModel({(x.kind, x.role, x.value): x.n for x in sums})


def _in_order(turns: DataFrame) -> DataFrame:
    """Transcripts whole and in order; rows without an id are dealt out each on its own."""
    lot = F.when(F.col("conv_id").isNull(), F.xxhash64("turn", "text")).otherwise(F.xxhash64("conv_id"))
    return turns.withColumn("_lot", lot).repartition("_lot").sortWithinPartitions("_lot", "conv_id", "turn", "text").drop("_lot")


def roles(turns: DataFrame, model: RoleModel) -> DataFrame:
    """conv_id, turn, role found, rendered turn, for blocks in order of turn; ``role`` is not read."""
    spark = turns.sparkSession
    prepare(spark)
    held = spark.sparkContext.broadcast(model)
    ids, turn = turns.schema["conv_id"].dataType, turns.schema["turn"].dataType
    schema = pa.schema([("conv_id", _arrow(ids)), ("turn", _arrow(turn)), ("role_found", pa.string()), ("rendered", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hmm = held.value

        def out() -> Iterator[tuple]:
            waiting: deque[tuple] = deque()
            path, last = Path(hmm), None
            for row in rows_of(batches, "conv_id", "turn", "text"):
                if last is not None and (row[0] is None or row[0] != last[0]):
                    yield from _turns(waiting, path.rest())
                    path = Path(hmm)
                path.add(hmm.emission(row[2]))
                waiting.append(row)
                last = row
                if len(path.back) >= SETTLE and len(path.back) % SETTLE == 0:
                    yield from _turns(waiting, path.decided())
            yield from _turns(waiting, path.rest())

        return batched(out(), schema)

    ordered = _in_order(turns.select("conv_id", "turn", "text"))
    return ordered.mapInArrow(run, f"conv_id {ids.simpleString()}, turn {turn.simpleString()}, role_found string, rendered string")


def _turns(waiting: deque[tuple], path: list[int]) -> Iterator[tuple]:
    """The first blocks that wait, with their roles."""
    for state in path:
        conv_id, turn, text = waiting.popleft()
        yield conv_id, turn, ROLES[state], render(ROLES[state], text)


def parse_transcripts(docs: DataFrame, model: RoleModel) -> DataFrame:
    """Raw transcripts (conv_id, text) to canonical turns."""
    prepare(docs.sparkSession)
    kind = docs.schema["conv_id"].dataType
    schema = pa.schema([("conv_id", _arrow(kind)), ("turn", pa.int64()), ("role_found", pa.string()), ("rendered", pa.string())])
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            for conv_id, text in rows_of(batches, "conv_id", "text"):
                blocks = split_transcript(text)
                path = held.value.viterbi(held.value.emission(b) for b in blocks)
                for k, (b, state) in enumerate(zip(blocks, path, strict=True)):
                    yield conv_id, k, ROLES[state], render(ROLES[state], b)

        return batched(out(), schema)

    return docs.select("conv_id", "text").mapInArrow(run, f"conv_id {kind.simpleString()}, turn long, role_found string, rendered string")


def digest(turns: DataFrame) -> DataFrame:
    """Roles of all turns by a model of the conversations whose crc32 modulo 5 is not 0."""
    training = is_trained_on(F.col("conv_id"), DIVISOR, HELD_OUT)
    model = learn(turns.where(training))
    found = roles(turns.select("conv_id", "turn", "text"), model)
    text = F.col("rendered").cast("binary")
    return found.select("conv_id", "turn", (~training).alias("held_out"), "role_found", F.length("rendered").cast("long").alias("rendered_chars"), F.crc32(text).alias("rendered_crc32"))
