"""The on-line grammar inducer: a Python kernel, linear in the number of tokens.

Symbols live in parallel lists (left, right, value); a rule is a ring closed by a guard. Values are even for terminals
and odd for rules. Two properties hold after every token: no pair of neighbours occurs twice without overlap, and every rule but the start
rule is used at least twice.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

import numpy as np


_MIX = 0x19E3779B1  # odd, and more than any symbol: a pair (a, b) is the key a * _MIX + b, whose low bits depend on both


class OnlineInducer:
    def __init__(self):
        self.left: list[int] = [0]
        self.right: list[int] = [0]
        self.value: list[int] = [-1]
        self.free: list[int] = []
        self.pairs: dict[int, int] = {}
        self.guard: list[int] = [0]
        self.uses: list[int] = [0]

    def feed(self, token: int):
        """Append a terminal (an id from 0)."""
        self.extend((token,))

    def extend(self, tokens: Iterable[int]):
        """Append terminals in turn. One function with local names and no calls in its inner steps, since calls were most of the time.

        Where two symbols that follow each other are parted, their pair leaves the table if it is the one recorded there. Inside a run of three equal symbols the
        overlapping pair comes back into it.
        """
        left, right, value, free, pairs, guard, uses = self.left, self.right, self.value, self.free, self.pairs, self.guard, self.uses
        get, put, take, mix, gone = pairs.get, free.append, free.pop, _MIX, -(1 << 60)

        def node(v: int) -> int:
            if free:
                i = take()
                value[i] = v
                return i
            left.append(-1)
            right.append(-1)
            value.append(v)
            return len(value) - 1

        def match(new: int, old: int):
            before, other = left[old], right[old]
            if value[before] < 0 and before == right[other]:
                rule = -1 - value[before]
                g = guard[rule]
                replace(new, rule)
            else:
                rule, v, u = len(guard), value[old], value[other]
                if len(free) > 2:
                    g, i, j = take(), take(), take()
                    value[g], value[i], value[j] = -1 - rule, v, u
                else:
                    g, i, j = node(-1 - rule), node(v), node(u)
                guard.append(g)
                uses.append(0)
                right[g] = left[j] = i
                left[g] = right[i] = j
                left[i] = right[j] = g
                if v & 1:
                    uses[v >> 1] += 1
                if u & 1:
                    uses[u >> 1] += 1
                replace(old, rule)
                replace(new, rule)
                first = right[g]
                pairs[value[first] * mix + value[right[first]]] = first
            v = value[right[g]]
            if v > 0 and v & 1 and uses[v >> 1] == 1:
                retire(right[g])
            v = value[left[g]]
            if v > 0 and v & 1 and uses[v >> 1] == 1:
                retire(left[g])

        def replace(i: int, rule: int):
            """Put the rule in place of the pair at node i."""
            p, j = left[i], right[i]
            q, l = right[j], left[p]  # noqa: E741
            pv, iv, jv, qv = value[p], value[i], value[j], value[q]
            alike = pv >= 0 and value[l] == pv
            # the pair's first symbol leaves
            if pv >= 0:
                key = pv * mix + iv
                if get(key) == p:
                    del pairs[key]
            if iv == jv == qv:
                pairs[jv * mix + jv] = j
            if alike and iv == pv:
                pairs[pv * mix + pv] = l
            key = iv * mix + jv
            if get(key) == i:
                del pairs[key]
            if iv & 1:
                uses[iv >> 1] -= 1
            # the second leaves
            if pv >= 0:
                key = pv * mix + jv
                if get(key) == p:
                    del pairs[key]
            if qv >= 0:
                if jv == qv and value[right[q]] == qv:
                    pairs[qv * mix + qv] = q
                if alike and jv == pv:
                    pairs[pv * mix + pv] = l
                key = jv * mix + qv
                if get(key) == j:
                    del pairs[key]
                # the rule comes in between
                if pv >= 0:
                    key = pv * mix + qv
                    if get(key) == p:
                        del pairs[key]
                    if alike and qv == pv:
                        pairs[pv * mix + pv] = l
            elif alike and jv == pv:
                pairs[pv * mix + pv] = l
            if jv & 1:
                uses[jv >> 1] -= 1
            left[i] = right[i] = -1
            value[i] = gone
            put(i)
            value[j] = r = rule << 1 | 1
            left[j], right[p] = p, j
            uses[rule] += 1
            if pv >= 0:
                key = pv * mix + r
                seen = get(key)
                if seen is None:
                    pairs[key] = p
                elif seen != p and right[seen] != p and j != seen:
                    match(p, seen)
                    return
            if qv >= 0:
                key = r * mix + qv
                seen = get(key)
                if seen is None:
                    pairs[key] = j
                elif seen != j and right[seen] != j and q != seen:
                    match(j, seen)

        def retire(i: int):
            """Unfold at node i, its only use, a rule that is no longer worth having."""
            rule = value[i] >> 1
            g = guard[rule]
            first, last = right[g], left[g]
            before, after = left[i], right[i]
            bv, iv, av, fv, lv = value[before], value[i], value[after], value[first], value[last]
            if bv >= 0:
                key = bv * mix + iv
                if get(key) == before:
                    del pairs[key]
            if av >= 0:
                key = iv * mix + av
                if get(key) == i:
                    del pairs[key]
            left[i] = right[i] = left[g] = right[g] = guard[rule] = -1
            value[i] = value[g] = gone
            put(i)
            put(g)
            uses[rule] = 0
            right[before], left[first] = first, before
            right[last], left[after] = after, last
            if av >= 0:
                pairs[lv * mix + av] = last
            if bv >= 0:
                pairs.setdefault(bv * mix + fv, before)

        g = guard[0]
        for token in tokens:
            last, v = left[g], token << 1
            if free:
                i = take()
                value[i], left[i], right[i] = v, last, g
            else:
                i = len(value)
                value.append(v)
                left.append(last)
                right.append(g)
            right[last] = left[g] = i
            a = value[last]
            if a >= 0:
                key = a * mix + v
                seen = get(key)
                if seen is None:
                    pairs[key] = last
                elif seen != last and right[seen] != last and i != seen:
                    match(last, seen)

    # -- results

    def bodies(self) -> dict[int, list[int]]:
        """Right side of each rule in use, 0 the start rule; values as fed: even 2 x token, odd 2 x rule + 1."""
        out = {}
        for rule, g in enumerate(self.guard):
            if g < 0:
                continue
            body, i = [], self.right[g]
            while i != g:
                body.append(self.value[i])
                i = self.right[i]
            out[rule] = body
        return out


def _renumbered(bodies: dict[int, list[int]]) -> dict[int, list[int]]:
    name = {r: i for i, r in enumerate(sorted(bodies))}
    return {name[r]: [(name[v >> 1] << 1) | 1 if v & 1 else v for v in body] for r, body in bodies.items()}


def induce(tokens: Sequence[int]) -> dict[int, list[int]]:
    """Grammar of a token sequence, rules renumbered 0, 1, 2 .. in order of creation."""
    kernel = OnlineInducer()
    kernel.extend(tokens)
    return _renumbered(kernel.bodies())


def induce_trace(tokens: Sequence[int]) -> Iterator[dict[int, list[int]]]:
    """The grammar after each token, from one inducer."""
    kernel = OnlineInducer()
    for t in tokens:
        kernel.feed(t)
        yield _renumbered(kernel.bodies())


def rule_order(bodies: dict[int, list[int]]) -> list[int]:
    """Rules, each after all rules that it uses."""
    done, out = set(), []
    for root in bodies:
        stack = [(root, False)]
        while stack:
            r, ready = stack.pop()
            if ready:
                out.append(r)
                continue
            if r in done:
                continue
            done.add(r)
            stack.append((r, True))
            stack += [(v >> 1, False) for v in bodies[r] if v & 1 and v >> 1 not in done]
    return out


def expand(bodies: dict[int, list[int]]) -> list[int]:
    """The original tokens."""
    known: dict[int, list[int]] = {}
    for r in rule_order(bodies):
        known[r] = [t for v in bodies[r] for t in (known[v >> 1] if v & 1 else (v >> 1,))]
    return known[0]


def token_depth(bodies: dict[int, list[int]]) -> np.ndarray:
    """Number of rules over each token in the derivation, the start rule not counted. A rule's depths are kept up to its last use only."""
    known: dict[int, np.ndarray] = {}
    left = [0] * (max(bodies) + 1)
    for body in bodies.values():
        for v in body:
            if v & 1:
                left[v >> 1] += 1
    for r in rule_order(bodies):
        parts, run = [], 0
        for v in bodies[r]:
            if v & 1:
                if run:
                    parts.append(np.zeros(run, np.int32))
                    run = 0
                v >>= 1
                left[v] -= 1
                parts.append((known[v] if left[v] else known.pop(v)) + 1)
            else:
                run += 1
        if run:
            parts.append(np.zeros(run, np.int32))
        known[r] = np.concatenate(parts) if parts else np.zeros(0, np.int32)
    return known[0]


def instances(bodies: dict[int, list[int]]) -> list[tuple[int, int, int]]:
    """Every occurrence (rule, first token, last token), nested ones included, the start rule left out; in order of first token, then longest."""
    size: dict[int, int] = {}
    for r in rule_order(bodies):
        size[r] = sum(size[v >> 1] if v & 1 else 1 for v in bodies[r])
    out, stack = [], [(0, 0)]
    while stack:
        r, at = stack.pop()
        if r:
            out.append((r, at, at + size[r] - 1))
        for v in bodies[r]:
            if v & 1:
                stack.append((v >> 1, at))
            at += size[v >> 1] if v & 1 else 1
    return sorted(out, key=lambda x: (x[1], -x[2], x[0]))
