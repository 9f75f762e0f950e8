"""Stateful streaming operators: symbols and grammars of series that arrive bit by bit.

Input rows (series_id, pos, x) of a series may come in any order within the stream; a position is taken up once all before it have come, so the
results do not depend on how the input was cut into batches. What waits is kept in the state; its size follows the disorder, not the stream.
"""

from __future__ import annotations

import json
import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from rarespan.operators import kernel
from rarespan.operators.inducer import OnlineInducer
from rarespan.schemas import DENSITY_RUN, TOKEN


def symbols(stream: DataFrame, n: int, params: list[tuple[int, int]], patience_ms: int | None = None) -> DataFrame:
    """TOKEN rows of a stream, runs collapsed: a token is emitted when its first window is complete.

    The state of a series holds its last n - 1 values, the last word of every resolution and what came too early. A missing position holds up
    its series; with ``patience_ms``, once nothing has come for so long (processing time), the series goes on at the first position that waits,
    with no window across the gap. Positions that come again, or after they were passed over, are dropped.
    """
    a_max = max(a for _, a in params)

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = json.loads(state.get[0]) if state.exists else {"next": 1, "tail": [], "wait": {}, "last": {}}
        wait = {int(k): v for k, v in held["wait"].items()}
        if state.hasTimedOut and wait:
            held |= {"next": min(wait), "tail": [], "last": {}}
        else:
            for pdf in frames:
                wait.update((p, x) for p, x in zip(pdf["pos"].tolist(), pdf["x"].tolist(), strict=True) if p >= held["next"])
        fresh = []
        while held["next"] in wait:
            fresh.append(wait.pop(held["next"]))
            held["next"] += 1
        x = np.array(held["tail"] + fresh, np.int64)
        out = []
        if fresh and len(x) >= n:
            start = held["next"] - len(x)
            for w, a, at, words in kernel.chunk_tokens(x, n, len(x), params, a_max):
                texts = words.astype(f"U{w}").tolist()
                for i, word in zip(at.tolist(), texts, strict=True):
                    if held["last"].get(f"{w}:{a}") != word:
                        out.append((key[0], w, a, start + i, word))
                        held["last"][f"{w}:{a}"] = word
        held["tail"] = x[max(0, len(x) - n + 1) :].tolist()
        held["wait"] = wait
        state.update((json.dumps(held),))
        if wait and patience_ms:
            state.setTimeoutDuration(patience_ms)
        yield pd.DataFrame(out, columns=["series_id", "w", "a", "pos", "word"])

    timeout = GroupStateTimeout.ProcessingTimeTimeout if patience_ms else GroupStateTimeout.NoTimeout
    return stream.groupBy("series_id").applyInPandasWithState(run, TOKEN, "held string", "append", timeout)


class _Open:
    """An open grammar: the inducer with its rules and pairs, the terminals met so far and where each token begins. ``carried``: its only token is the
    rest of one whose grammar was closed."""

    def __init__(self):
        self.inducer, self.names, self.pos, self.last, self.carried = OnlineInducer(), {}, [], None, False

    def feed(self, pos: int, word: str):
        if self.carried and len(self.pos) == 1 and pos == self.pos[0]:
            self.__init__()
        if word != self.last:
            self.inducer.feed(self.names.setdefault(word, len(self.names)))
            self.pos.append(pos)
            self.last = word

    def runs(self, end: int) -> list[tuple[int, int, int]]:
        """(lo, hi, density) up to ``end``."""
        depth = kernel.token_depth(self.inducer.bodies())
        first = np.flatnonzero(np.concatenate(([True], depth[1:] != depth[:-1])))
        lo = np.array(self.pos, np.int64)[first]
        return list(zip(lo.tolist(), [*(lo[1:] - 1).tolist(), end], depth[first].tolist(), strict=True))


def grammars(tokens: DataFrame, most: int = 100_000, idle_ms: int | None = None) -> DataFrame:
    """DENSITY_RUN rows of closed grammars: a (series, w, a) feeds its tokens to the inducer kept in its state, each token once; after ``most`` tokens the
    grammar is closed, its final density is emitted and a new one begins at the next token, which bounds the state. ``part`` boundaries of batch
    runs are by position instead.

    With ``idle_ms``, a key that gets nothing for so long (processing time) closes its grammar up to its last token's position; the positions from there to the next token
    begin the next grammar, so the emitted runs leave no gap. Tokens of a key must arrive in order of position (as ``symbols`` emits them).
    """

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held = pickle.loads(state.get[0]) if state.exists else _Open()  # our own checkpoint's bytes
        out = []
        if state.hasTimedOut:
            end, word = held.pos[-1], held.last
            out += held.runs(end)
            held = _Open()
            held.feed(end + 1, word)
            held.carried = True
        else:
            came = pd.concat(list(frames)).sort_values("pos")
            for pos, word in zip(came["pos"].tolist(), came["word"].tolist(), strict=True):
                if len(held.pos) == most and word != held.last:
                    out += held.runs(pos - 1)
                    held = _Open()
                held.feed(pos, word)
        state.update((pickle.dumps(held),))
        if idle_ms and held.pos and not (held.carried and len(held.pos) == 1):
            state.setTimeoutDuration(idle_ms)
        yield pd.DataFrame([(*key, *r) for r in out], columns=["series_id", "w", "a", "lo", "hi", "d"])

    timeout = GroupStateTimeout.ProcessingTimeTimeout if idle_ms else GroupStateTimeout.NoTimeout
    return tokens.groupBy("series_id", "w", "a").applyInPandasWithState(run, DENSITY_RUN, "held binary", "append", timeout)


def provisional_depth(words: list[str]) -> list[list[int]]:
    """Density of every token after each arrival; an open grammar's values may still change, those of a closed one are final."""
    kernel_state, names, out = OnlineInducer(), {}, []
    for k, w in enumerate(words):
        kernel_state.feed(names.setdefault(w, len(names)))
        out.append(kernel.token_depth(kernel_state.bodies()).tolist()[: k + 1])
    return out
