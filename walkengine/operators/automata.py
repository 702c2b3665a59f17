"""Fixed patterns of the workloads, as automata (runs depend on the automaton) and as text."""

from walkengine.lang.automata import Nfa

_HS = lambda p, q: [(p, "h", q), (p, "s", q)]
P1 = Nfa.of(2, [(0, "h", 0), (0, "s", 1), *_HS(1, 1)], [0], [1])
P2 = Nfa.of(2, [*_HS(0, 0), (0, "s", 1), *_HS(1, 1)], [0], [1])
P3 = Nfa.of(3, [*_HS(0, 0), (0, "s", 1), *_HS(1, 2)], [0], [2])
P4 = Nfa.of(6, [m for i in range(5) for m in _HS(i, i + 1)], [0], [5])
PATTERNS = {"p1": P1, "p2": P2, "p3": P3, "p4": P4}
TEXT = {"p1": "h* s (h|s)*", "p2": "(h|s)* s (h|s)*", "p3": "(h|s)* s (h|s)", "p4": "(h|s){5}"}
