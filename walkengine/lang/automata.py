"""Nondeterministic automata over labels, and what patterns need of them.  All of it is as small as the pattern."""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass, field
from functools import reduce
from itertools import product

from walkengine.lang.patterns import Ast, parse_pattern


@dataclass(frozen=True)
class Nfa:
    """States 0..n-1; ``moves`` holds (from, label, to), ``eps`` spontaneous moves (from, to)."""

    n: int
    moves: frozenset[tuple[int, str, int]]
    initial: frozenset[int]
    final: frozenset[int]
    eps: frozenset[tuple[int, int]] = field(default_factory=frozenset)

    @staticmethod
    def of(n: int, moves, initial, final, eps=()) -> Nfa:
        return Nfa(n, frozenset(moves), frozenset(initial), frozenset(final), frozenset(eps))

    @property
    def alphabet(self) -> tuple[str, ...]:
        return tuple(sorted({a for _, a, _ in self.moves}))

    def size(self) -> int:
        return len(self.alphabet) + self.n + len(self.moves) + len(self.eps) + len(self.initial) + len(self.final)

    def mask(self, states) -> int:
        return reduce(lambda m, q: m | 1 << q, states, 0)

    def closure(self, states) -> frozenset[int]:
        seen, work = set(states), list(states)
        while work:
            p = work.pop()
            for a, b in self.eps:
                if a == p and b not in seen:
                    seen.add(b)
                    work.append(b)
        return frozenset(seen)

    def step(self, states, labels) -> frozenset[int]:
        return frozenset(q for p, a, q in self.moves if p in states and a in labels)

    def accepts(self, word) -> bool:
        """``word``: labels, or sets of labels of which any may be read."""
        now = self.closure(self.initial)
        for letter in word:
            now = self.closure(self.step(now, {letter} if isinstance(letter, str) else set(letter)))
        return bool(now & self.final)

    def is_deterministic(self) -> bool:
        pairs = [(p, a) for p, a, _ in self.moves]
        return not self.eps and len(self.initial) <= 1 and len(pairs) == len(set(pairs))

    def is_unambiguous(self) -> bool:
        """No word has two accepting runs: the self-product reaches no useful pair of different states."""
        nfa = trim_states(close_spontaneous(self))
        by = defaultdict(list)
        for p, a, q in nfa.moves:
            by[p, a].append(q)
        grow = lambda starts, step: _reach(starts, step)
        forward = grow(
            set(product(nfa.initial, nfa.initial)),
            lambda x: {(q, r) for a in nfa.alphabet for q in by[x[0], a] for r in by[x[1], a]},
        )
        back = defaultdict(list)
        for p, a, q in nfa.moves:
            back[q, a].append(p)
        useful = grow(
            set(product(nfa.final, nfa.final)),
            lambda x: {(q, r) for a in nfa.alphabet for q in back[x[0], a] for r in back[x[1], a]},
        )
        return all(p == q for p, q in forward & useful)


def _reach(starts: set, step) -> set:
    seen, work = set(starts), list(starts)
    while work:
        for y in step(work.pop()):
            if y not in seen:
                seen.add(y)
                work.append(y)
    return seen


def close_spontaneous(nfa: Nfa) -> Nfa:
    """The same language without spontaneous moves: arrivals and starts are closed under them."""
    if not nfa.eps:
        return nfa
    near = {q: nfa.closure({q}) for q in range(nfa.n)}
    moves = {(p, a, r) for p, a, q in nfa.moves for r in near[q]}
    return Nfa.of(nfa.n, moves, nfa.closure(nfa.initial), nfa.final)


def trim_states(nfa: Nfa) -> Nfa:
    """Without states that no start reaches or that reach no end; states are numbered anew."""
    out, back = defaultdict(set), defaultdict(set)
    for p, q in [(p, q) for p, _, q in nfa.moves] + list(nfa.eps):
        out[p].add(q)
        back[q].add(p)
    keep = sorted(_reach(set(nfa.initial), out.__getitem__) & _reach(set(nfa.final), back.__getitem__))
    name = {q: i for i, q in enumerate(keep)}
    return Nfa.of(
        len(keep),
        {(name[p], a, name[q]) for p, a, q in nfa.moves if p in name and q in name},
        {name[q] for q in nfa.initial if q in name},
        {name[q] for q in nfa.final if q in name},
        {(name[p], name[q]) for p, q in nfa.eps if p in name and q in name},
    )


def _letters(ast: Ast, alphabet) -> list[str]:
    return [ast.label] if ast.kind == "label" else [a for a in alphabet if ast.kind == "any" or a != ast.label]


def inductive_nfa(ast: Ast, alphabet=()) -> Nfa:
    """Linear-size construction along the pattern, with spontaneous moves; one start and one end a sub-pattern."""
    moves, eps, count = set(), set(), 0

    def fresh() -> int:
        nonlocal count
        count += 1
        return count - 1

    def build(node: Ast) -> tuple[int, int]:
        a, b = fresh(), fresh()
        if node.kind == "empty":
            eps.add((a, b))
        elif node.kind in ("label", "any", "other"):
            moves.update((a, x, b) for x in _letters(node, alphabet))
        elif node.kind == "alt":
            for part in node.parts:
                s, t = build(part)
                eps.update(((a, s), (t, b)))
        elif node.kind == "cat":
            at = a
            for part in node.parts:
                s, t = build(part)
                eps.add((at, s))
                at = t
            eps.add((at, b))
        else:
            s, t = build(node.parts[0])
            eps.update(((a, b), (a, s), (t, s), (t, b)))
        return a, b

    start, end = build(ast)
    return Nfa.of(count, moves, {start}, {end}, eps)


def position_nfa(ast: Ast, alphabet=()) -> Nfa:
    """One state for every label of the pattern and one start, without spontaneous moves."""
    letters: list[list[str]] = [[]]
    follow: set[tuple[int, int]] = set()

    def walk(node: Ast) -> tuple[bool, set[int], set[int]]:
        """(matches the empty word, first positions, last positions)."""
        if node.kind == "empty":
            return True, set(), set()
        if node.kind in ("label", "any", "other"):
            letters.append(_letters(node, alphabet))
            here = {len(letters) - 1}
            return False, here, here
        parts = [walk(p) for p in node.parts]
        if node.kind == "alt":
            return any(p[0] for p in parts), set().union(*(p[1] for p in parts)), set().union(*(p[2] for p in parts))
        if node.kind == "star":
            _, first, last = parts[0]
            follow.update(product(last, first))
            return True, first, last
        empty, first, last = True, set(), set()
        for e, f, l in parts:
            follow.update(product(last, f))
            first |= f if empty else set()
            last = l | (last if e else set())
            empty &= e
        return empty, first, last

    empty, first, last = walk(ast)
    follow.update((0, q) for q in first)
    moves = {(p, a, q) for p, q in follow for a in letters[q]}
    return Nfa.of(len(letters), moves, {0}, last | ({0} if empty else set()))


def determinize(nfa: Nfa, by_label_sets: bool = False) -> Nfa:
    """Subset construction; ``by_label_sets`` reads whole label sets (named ``a+b``), as edges with several labels need."""
    nfa = close_spontaneous(nfa)
    base = nfa.alphabet
    letters = {a: {a} for a in base}
    if by_label_sets:
        letters = {"+".join(s): set(s) for s in (tuple(a for i, a in enumerate(base) if k >> i & 1) for k in range(1, 1 << len(base)))}
    name, work, moves = {nfa.initial: 0}, [nfa.initial], set()
    while work:
        now = work.pop()
        for letter, labels in letters.items():
            then = nfa.step(now, labels)
            if then:
                if then not in name:
                    name[then] = len(name)
                    work.append(then)
                moves.add((name[now], letter, name[then]))
    return Nfa.of(len(name), moves, {0} if nfa.initial else (), {i for s, i in name.items() if s & nfa.final})


def reverse(nfa: Nfa) -> Nfa:
    return Nfa.of(nfa.n, {(q, a, p) for p, a, q in nfa.moves}, nfa.final, nfa.initial, {(q, p) for p, q in nfa.eps})


def minimize(nfa: Nfa) -> Nfa:
    """The smallest deterministic automaton: determinise the reverse twice."""
    return trim_states(determinize(reverse(trim_states(determinize(reverse(nfa))))))


def equivalent(a: Nfa, b: Nfa) -> bool:
    a, b = close_spontaneous(a), close_spontaneous(b)
    letters = set(a.alphabet) | set(b.alphabet)
    pairs = _reach({(a.initial, b.initial)}, lambda x: {(a.step(x[0], {l}), b.step(x[1], {l})) for l in letters})
    return all(bool(p & a.final) == bool(q & b.final) for p, q in pairs)


def compile_pattern(pattern: str | Ast | Nfa, alphabet=(), construction: str = "inductive") -> Nfa:
    """An automaton without spontaneous moves or useless states.  ``construction``: inductive or position."""
    if not isinstance(pattern, Nfa):
        ast = parse_pattern(pattern) if isinstance(pattern, str) else pattern
        pattern = (inductive_nfa if construction == "inductive" else position_nfa)(ast, alphabet)
    return trim_states(close_spontaneous(pattern))
