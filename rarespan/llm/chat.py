"""Chat formatting: roles of a transcript's lines by a hidden Markov model, then canonical turns.

States are (role, first line of a turn or not). A line emits a few discrete features: its speaker marker, whether a gap precedes it,
its length, whether it asks, whether it opens the transcript, and how long its paragraph block is. Start, transition and
emission tables are counted from labelled conversations. Viterbi finds the most probable states.

Long transcripts are cut into chunks. The best scores between a chunk's entry and exit states form a
matrix, and such matrices compose by max-plus products, so the boundary states of all chunks are exact, however long the
transcript is; each chunk is then decoded between its boundary states by a task of its own.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rarespan.llm.sampling import bounded
from rarespan.runtime import cut, shuffle_partitions

# The roles and the speaker markers known for each.
ROLES = ("system", "user", "assistant")
_MARKERS = {
    "system": ("system", "sys", "instructions"),
    "user": ("user", "human", "q", "question", "customer", "me", "you"),
    "assistant": ("assistant", "ai", "bot", "a", "answer", "agent", "model"),
}
_MARK = re.compile(r"^\s*(?:<\|(\w+)\|>|\[(\w+)\]|#{2,3}\s*(\w+)\s*:?|\**(\w+)\**\s*:)\s*(.*)$", re.S)
_ROLE_OF = {name: i for i, names in enumerate(_MARKERS.values()) for name in names}
STATES = 2 * len(ROLES)
CHUNK = 256  # turns
SHAPE = (4, 2, 8, 2, 2, 6)  # values of each feature
SAMPLE = 20_000  # at most so many labelled turns are learnt from
CHARACTERS = 20_000_000  # and so many characters


def marker(line: str) -> tuple[int, str]:
    """(1 + role of the line's speaker marker or 0, the line without it)."""
    m = _MARK.match(line)
    if m:
        name = next(g for g in m.groups()[:4] if g is not None).lower()
        if name in _ROLE_OF:
            return 1 + _ROLE_OF[name], m[5]
    return 0, line


def features(lines: list[str], gaps: list[bool], opens: bool) -> np.ndarray:
    """One row of discrete features a line; ``opens`` tells that the first line begins the transcript."""
    out = np.zeros((len(lines), len(SHAPE)), np.int64)
    block = np.cumsum([bool(g) or i == 0 for i, g in enumerate(gaps)]) - 1
    size = np.bincount(block, [len(x) for x in lines]) if lines else np.zeros(0)
    for i, line in enumerate(lines):
        mark, rest = marker(line)
        out[i] = (
            mark,
            bool(gaps[i]),
            min(7, max(0, len(rest).bit_length() - 3)),
            rest.rstrip().endswith("?"),
            opens and i == 0,
            min(5, max(0, int(size[block[i]]).bit_length() - 5)),
        )
    return out


@dataclass
class RoleModel:
    start: np.ndarray
    move: np.ndarray
    emit: list[np.ndarray]

    def emissions(self, x: np.ndarray) -> np.ndarray:
        return sum(table[:, x[:, j]].T for j, table in enumerate(self.emit))

    def span(self, e: np.ndarray) -> np.ndarray:
        """Max-plus matrix of a chunk: best score of leaving in column state after entering, before its first line, from row state."""
        best = self.move + e[0]
        for row in e[1:]:
            best = (best[:, :, None] + self.move[None]).max(1) + row
        return best

    def decode(self, e: np.ndarray, entry: int, leave: int) -> np.ndarray:
        """States of a chunk's lines; entry -1: the transcript begins here; leave -1: any last state."""
        score = (self.start if entry < 0 else self.move[entry]) + e[0]
        back = np.zeros((len(e), STATES), np.int64)
        for i in range(1, len(e)):
            path = score[:, None] + self.move
            back[i] = path.argmax(0)
            score = path.max(0) + e[i]
        out = np.zeros(len(e), np.int64)
        out[-1] = score.argmax() if leave < 0 else leave
        for i in range(len(e) - 1, 0, -1):
            out[i - 1] = back[i, out[i]]
        return out


def split_lines(text: str | None) -> list[str]:
    return (text or "").split("\n")


def fit(turns: list[tuple]) -> RoleModel:
    """Tables with add-one smoothing from labelled turns (conversation, turn, role, text) in order; unknown roles are skipped."""
    start, move = np.ones(STATES), np.ones((STATES, STATES)) * 0.1
    emit = [np.ones((STATES, n)) for n in SHAPE]
    held, lines, gaps, states = None, [], [], []

    def count():
        if not lines:
            return
        x = features(lines, gaps, True)
        start[states[0]] += 1
        for a, b in zip(states, states[1:], strict=False):
            move[a, b] += 1
        for j in range(len(SHAPE)):
            np.add.at(emit[j], (states, x[:, j]), 1)

    for conv, _, role, text in turns:
        if conv != held:
            count()
            held, lines, gaps, states = conv, [], [], []
        if role not in ROLES:
            continue
        for i, line in enumerate(split_lines(text)):
            lines.append(line)
            gaps.append(i == 0)
            states.append(2 * ROLES.index(role) + (i > 0))
    count()
    norm = lambda t: np.log(t / t.sum(-1, keepdims=True))
    return RoleModel(norm(start), norm(move), [norm(t) for t in emit])


def train(turns: DataFrame, is_training: Column, most: int = SAMPLE, characters: int = CHARACTERS) -> RoleModel:
    """A model from whole labelled conversations, taken in the order of their ids' hashes as long as they have at most ``most`` turns and ``characters`` together.

    One that does not fit is passed over, never cut; the sample bounds what is learnt from, not what is parsed.
    """
    rows = turns.where(is_training & F.col("conv_id").isNotNull() & F.col("turn").isNotNull())
    rows = rows.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
    sizes = rows.groupBy("conv_id").agg(F.count("*").alias("n"), F.sum(F.coalesce(F.char_length("text"), F.lit(0)) + 1).alias("c"))
    chosen, n, c = [], 0, 0
    for r in bounded(sizes.where((F.col("n") <= most) & (F.col("c") <= characters)), most // 4, "conv_id").collect():
        if n + r["n"] <= most and c + r["c"] <= characters:
            chosen.append(r["conv_id"])
            n, c = n + r["n"], c + r["c"]
    some = turns.sparkSession.createDataFrame([(x,) for x in chosen], "conv_id long")
    got = rows.join(F.broadcast(some), "conv_id").orderBy(F.xxhash64("conv_id"), "conv_id", "turn", "role", F.xxhash64("text"))
    return fit([tuple(r) for r in got.collect()])


def parse(model: RoleModel, text: str | None) -> list[tuple[str, str]]:
    """Turns (role, text) of one raw transcript; blank lines are gaps. No text, no turns."""
    lines, gaps, gap = [], [], True
    for line in split_lines(text):
        if line.strip():
            lines.append(line)
            gaps.append(gap)
            gap = False
        else:
            gap = True
    if not lines:
        return []
    states = model.decode(model.emissions(features(lines, gaps, True)), -1, -1)
    turns: list[list] = []
    for i, (line, s) in enumerate(zip(lines, states.tolist(), strict=True)):
        role, inner = ROLES[s // 2], s % 2
        mark, rest = marker(line)
        line = rest if mark == 1 + s // 2 and not inner else line
        if turns and inner and turns[-1][0] == role:
            turns[-1][1] += ("\n\n" if gaps[i] else "\n") + line
        else:
            turns.append([role, line])
    return [(r, t.strip()) for r, t in turns]


def render(role: str, text: str) -> str:
    """The canonical form of one turn."""
    return f"<|{role}|>\n{text}<|end|>\n"


def parse_transcripts(docs: DataFrame, model: RoleModel, text_col: str = "text") -> DataFrame:
    """The documents with turns (array of role and text) and chat (their canonical rendering) added; null texts have no turns."""
    schema = "array<struct<role:string,text:string>>"

    @F.pandas_udf(schema)
    def turns(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: [{"role": r, "text": x} for r, x in parse(model, t)])

    form = F.array_join(F.transform("turns", lambda t: F.concat(F.lit("<|"), t["role"], F.lit("|>\n"), t["text"], F.lit("<|end|>\n"))), "")
    return docs.withColumn("turns", turns(F.col(text_col))).withColumn("chat", form)


def _groups(frames: Iterator[pd.DataFrame], keys: list[str]) -> Iterator[pd.DataFrame]:
    """Consecutive rows with equal keys, across batches."""
    held: pd.DataFrame | None = None
    for pdf in frames:
        if held is not None:
            pdf = pd.concat([held, pdf], ignore_index=True)
        if not len(pdf):
            continue
        k = pdf[keys].to_numpy()
        edge = np.flatnonzero(np.concatenate(([True], (k[1:] != k[:-1]).any(1))))
        for a, b in zip(edge[:-1], edge[1:], strict=True):
            yield pdf.iloc[a:b]
        held = pdf.iloc[edge[-1] :]
    if held is not None and len(held):
        yield held


def recover_roles(turns: DataFrame, model: RoleModel, chunk: int = CHUNK) -> DataFrame:
    """conv_id, turn, text, role_found, body for each turn: its role as the lines alone tell it; the given roles are not read. body is the text without a speaker marker of that role.

    A conversation is the sequence of its turns' lines, in order of turn, then text; each turn begins with a gap. Null texts are
    one empty line; rows with null conv_id or turn are left out; repeated rows are turns each for itself.
    """
    n = shuffle_partitions(turns.sparkSession)
    rows = turns.where("conv_id is not null and turn is not null").select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce("text", F.lit("")).alias("text")
    )
    first = rows.groupBy("conv_id").agg(F.min("turn").alias("first"), F.max("turn").alias("last"))
    rows = rows.join(first, "conv_id").withColumn("chunk", F.expr(f"turn div {chunk}")).withColumn("alone", F.expr(f"first div {chunk} = last div {chunk}"))
    dealt = rows.repartition(n, "conv_id", "chunk").sortWithinPartitions("conv_id", "chunk", "turn", "text")

    def lines_of(g: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
        lines, gaps, heads = [], [], []
        for text in g["text"]:
            heads.append(len(lines))
            own = split_lines(text)
            lines += own
            gaps += [True] + [False] * (len(own) - 1)
        opens = int(g["chunk"].iloc[0]) == int(g["first"].iloc[0]) // chunk
        return model.emissions(features(lines, gaps, opens)), np.array(heads)

    def matrices(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for g in _groups(frames, ["conv_id", "chunk"]):
            e, _ = lines_of(g)
            yield pd.DataFrame({"conv_id": [g["conv_id"].iloc[0]], "chunk": [g["chunk"].iloc[0]], "m": [model.span(e).ravel().tolist()], "s": [_from_start(model, e).tolist()]})

    def boundaries(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("chunk")
        m = [np.array(x).reshape(STATES, STATES) for x in pdf["m"]]
        score, back = np.array(pdf["s"].iloc[0]), []
        for step in m[1:]:
            path = score[:, None] + step
            back.append(path.argmax(0))
            score = path.max(0)
        state, leave = int(score.argmax()), []
        for b in reversed(back):
            leave.append(state)
            state = int(b[state])
        leave = [state, *reversed(leave)]
        return pd.DataFrame({"conv_id": pdf["conv_id"], "chunk": pdf["chunk"], "entry": [-1, *leave[:-1]], "leave": leave})

    def decode(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for g in _groups(frames, ["conv_id", "chunk"]):
            e, heads = lines_of(g)
            states = model.decode(e, int(g["entry"].iloc[0]), int(g["leave"].iloc[0]))[heads]
            bodies = [rest if mark == 1 + s // 2 else text for text, s, (mark, rest) in zip(g["text"], states.tolist(), map(marker, g["text"]), strict=True)]
            yield pd.DataFrame({"conv_id": g["conv_id"], "turn": g["turn"], "text": g["text"], "role_found": [ROLES[s // 2] for s in states], "body": bodies})

    out = "conv_id long, turn long, text string, role_found string, body string"
    short = dealt.where("alone").withColumn("entry", F.lit(-1)).withColumn("leave", F.lit(-1)).mapInPandas(decode, out)
    long = dealt.where("not alone")
    spans = long.mapInPandas(matrices, "conv_id long, chunk long, m array<double>, s array<double>")
    edges = spans.groupBy("conv_id").applyInPandas(boundaries, "conv_id long, chunk long, entry int, leave int")
    known = long.join(cut(edges), ["conv_id", "chunk"]).repartition(n, "conv_id", "chunk").sortWithinPartitions("conv_id", "chunk", "turn", "text")
    return short.unionByName(known.mapInPandas(decode, out))


def _from_start(model: RoleModel, e: np.ndarray) -> np.ndarray:
    score = model.start + e[0]
    for row in e[1:]:
        score = (score[:, None] + model.move).max(0) + row
    return score


def format_conversations(turns: DataFrame, folds: int = 5, held_out: int = 0) -> DataFrame:
    """conv_id, turn, held_out, role_found, rendered for each turn, by a model of the conversations outside the held-out fold.

    Null texts render as empty turns; rows with null conv_id or turn are left out; repeated rows give a row each; an empty table gives none; other columns are ignored.
    """
    fold = F.pmod(F.crc32(F.col("conv_id").cast("string")), F.lit(folds))
    model = train(turns, fold != held_out)
    found = recover_roles(turns, model)
    form = F.concat(F.lit("<|"), "role_found", F.lit("|>\n"), "body", F.lit("<|end|>\n"))
    return found.select("conv_id", "turn", (fold == held_out).alias("held_out"), "role_found", form.alias("rendered"))
