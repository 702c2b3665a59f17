"""Automata as Spark expressions over bit masks: bit q of a BIGINT stands for state q, bit i for label i."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from walkengine.lang.automata import Nfa

#: The largest bit of a BIGINT that is positive.
MAX_STATES = 62


def label_mask(labels: str | Column, alphabet: tuple[str, ...]) -> Column:
    """Labels (an array) as bits; labels beyond the alphabet count for nothing."""
    labels = F.col(labels) if isinstance(labels, str) else labels
    bits = [F.when(F.array_contains(labels, a), F.lit(1 << i)).otherwise(F.lit(0)) for i, a in enumerate(alphabet)]
    return reduce(lambda x, y: x.bitwiseOR(y), bits, F.lit(0)).cast("long")


def _moves(nfa: Nfa, alphabet: tuple[str, ...], backward: bool, states: Column, labels: Column) -> Column:
    if nfa.n > MAX_STATES:
        raise ValueError(f"state sets are kept in {MAX_STATES} bits; the automaton has {nfa.n} states")
    bit = {a: 1 << i for i, a in enumerate(alphabet)}
    groups: dict[tuple[int, int], int] = {}  # (label bits, arrival) -> departures
    for p, a, q in nfa.moves:
        if a in bit:
            start, end = (q, p) if backward else (p, q)
            groups[bit[a], end] = groups.get((bit[a], end), 0) | 1 << start
    by: dict[tuple[int, int], int] = {}  # (departures, arrivals) -> label bits
    for (labs, end), starts in groups.items():
        by[starts, 1 << end] = by.get((starts, 1 << end), 0) | labs
    merged: dict[tuple[int, int], int] = {}  # (departures, label bits) -> arrivals
    for (starts, end), labs in by.items():
        merged[starts, labs] = merged.get((starts, labs), 0) | end
    has = lambda c, m: c.bitwiseAND(F.lit(m).cast("long")) != 0
    parts = [
        F.when(has(states, s) & has(labels, l), F.lit(e).cast("long")).otherwise(F.lit(0).cast("long"))
        for (s, l), e in sorted(merged.items())
    ]
    return reduce(lambda x, y: x.bitwiseOR(y), parts, F.lit(0).cast("long"))


def step_expr(states: Column, labels: Column, nfa: Nfa, alphabet: tuple[str, ...]) -> Column:
    """States after an edge."""
    return _moves(nfa, alphabet, False, states, labels)


def inverse_step_expr(states: Column, labels: Column, nfa: Nfa, alphabet: tuple[str, ...]) -> Column:
    """States before an edge."""
    return _moves(nfa, alphabet, True, states, labels)


def closure_expr(states: Column, nfa: Nfa) -> Column:
    """The states and all that spontaneous moves reach from them; one test for each state that has such moves."""
    parts = [states]
    for p in sorted({p for p, _ in nfa.eps}):
        near = nfa.mask(nfa.closure({p}))
        parts.append(F.when(states.bitwiseAND(F.lit(1 << p).cast("long")) != 0, F.lit(near).cast("long")).otherwise(F.lit(0).cast("long")))
    return reduce(lambda x, y: x.bitwiseOR(y), parts)


def run_counts(counts: Column, labels: Column, nfa: Nfa, alphabet: tuple[str, ...], by: str = "words") -> Column:
    """Array of run counts before an edge from those after it; ``by``: words counts (label, move), states counts (from, to)."""
    bit = {a: 1 << i for i, a in enumerate(alphabet)}
    pairs: dict[tuple[int, int], int] = {}
    for p, a, q in nfa.moves:
        if a in bit:
            pairs[p, q] = pairs.get((p, q), 0) | bit[a]
    zero = F.lit(0).cast("decimal(38,0)")
    out = []
    for p in range(nfa.n):
        total = zero
        for (x, q), labs in sorted(pairs.items()):
            if x == p:
                both = labels.bitwiseAND(F.lit(labs).cast("long"))
                times = F.bit_count(both) if by == "words" else F.when(both != 0, 1).otherwise(0)
                total = (total + counts[q] * times.cast("decimal(3,0)")).cast("decimal(38,0)")
        out.append(total)
    return F.array(*out)
