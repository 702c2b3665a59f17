"""Lazy emission of one run inside one task, with counts of elementary steps.

Works on a run's links alone.  ``Emitter.walks`` is depth-first with constant delay; ``next_walk`` finds the answer after
a given one from the links and that answer only, by scanning or by pointers.  Options reproduce the slower variants that
the measures compare: browsing every in-edge, and scanning whole queues to merge equal edges.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkengine.core.search import AnswerEdges, Layers, answer_edges, answer_links
from walkengine.lang.automata import Nfa


class Emitter:
    def __init__(self, nfa: Nfa, alphabet: tuple[str, ...], links: list[tuple], target, level: int, mask: int, in_edges: dict | None = None):
        """``links``: (level, dst, edge_id, src, lab, src_mask, dst_mask).  ``in_edges``: all edges into a vertex, for browsing."""
        self.root, self.steps, self.calls, self.depth = (level, target, mask), 0, 0, 0
        bit = {a: 1 << i for i, a in enumerate(alphabet)}
        self.back = [(1 << q, bit[a], 1 << p) for p, a, q in nfa.moves if a in bit]
        self.known: dict[tuple[int, int], int] = {}
        by = defaultdict(list)
        for lv, dst, edge, src, lab, src_mask, dst_mask in links:
            by[lv, dst].append((edge, src, lab, src_mask, dst_mask))
        self.links = {k: sorted(v) for k, v in by.items()}
        self.queues = {
            (k, q): [i for i, x in enumerate(v) if x[4] >> q & 1] for k, v in self.links.items() for q in range(nfa.n)
        }
        self.place = {k: {x[0]: i for i, x in enumerate(v)} for k, v in self.links.items()}
        # after[k, q][i]: the first place beyond i with a link for state q (a place has one whether or not q uses it)
        self.after: dict[tuple, list[int]] = {}
        for (k, q), queue in self.queues.items():
            then, n = [len(queue)] * len(self.links[k]), len(queue)
            for h in range(n - 1, -1, -1):
                for i in range(queue[h - 1] if h else 0, queue[h]):
                    then[i] = h
            self.after[k, q] = then
        self.states = [tuple(q for q in range(nfa.n) if m >> q & 1) for m in range(1 << min(nfa.n, 12))] if nfa.n <= 12 else None
        self.n, self.in_edges = nfa.n, in_edges

    def before(self, mask: int, lab: int) -> int:
        key = mask, lab
        if key not in self.known:
            self.known[key] = sum({p for q, l, p in self.back if mask & q and lab & l})
        return self.known[key]

    def _looked(self, mask: int, lab: int) -> int:
        """Moves that a step from the link's end back looks at: those into a state of the set."""
        return sum(1 for q, _, _ in self.back if mask & q)

    def _of(self, mask: int):
        return self.states[mask] if self.states else [q for q in range(self.n) if mask >> q & 1]

    def _child(self, link: tuple, level: int, mask: int) -> tuple:
        self.steps += self._looked(mask, link[2])  # counted whether or not the answer is remembered
        return level - 1, link[1], self.before(mask, link[2]) & link[3]

    def children(self, node: tuple, after=None, compact: bool = True, merge: str = "heads") -> Iterator[tuple]:
        """(edge, child) in in-edge order, from beyond ``after``."""
        level, vertex, mask = node
        here, links = (level, vertex), self.links.get((level, vertex), [])
        if not compact:  # every in-edge of the vertex is looked at, used or not
            place = {x[0]: x for x in links}
            for edge in self.in_edges.get(vertex, []):
                self.steps += 1
                if (after is None or edge > after) and edge in place:
                    child = self._child(place[edge], level, mask)
                    if child[2]:
                        yield edge, child
            return
        heads = {q: 0 for q in self._of(mask)}
        if after is not None:
            for q in heads:
                heads[q] = self.after[here, q][self.place[here][after]]  # one look-up by pointer
                self.steps += 1
        while True:
            best = None
            for q, h in heads.items():
                queue = self.queues.get((here, q), ())
                self.steps += 1 if merge == "heads" else max(1, len(queue))
                if h < len(queue) and (best is None or queue[h] < best):
                    best = queue[h]
            if best is None:
                return
            for q in heads:
                queue = self.queues.get((here, q), ())
                if heads[q] < len(queue) and queue[heads[q]] == best:
                    heads[q] += 1
            child = self._child(links[best], level, mask)
            if child[2]:
                yield links[best][0], child

    def walks(self, compact: bool = True, merge: str = "heads", after: list | None = None) -> Iterator[tuple]:
        """Edge paths, first edge first, in lexicographic order read from the target; beyond ``after`` if given."""
        if self.root[0] == 0:
            if after is None:
                yield ()
            return
        path: list = []
        stack = [self.children(self.root, None, compact, merge)]
        if after is not None:
            stack, node = [], self.root
            for edge in reversed(after):  # replay the given answer to restore the cursors
                stack.append(self.children(node, edge, compact, merge))
                path.append(edge)
                at = node[0], node[1]
                node = self._child(self.links[at][self.place[at][edge]], node[0], node[2])
            path.pop()
        while stack:
            found = next(stack[-1], None)
            if found is None:
                stack.pop()
                if path:
                    path.pop()
                continue
            self.calls += 1
            edge, child = found
            path.append(edge)
            if child[0] == 0:
                self.depth = len(stack)
                yield tuple(reversed(path))
                path.pop()
            else:
                stack.append(self.children(child, None, compact, merge))

    def next_walk(self, previous: tuple, method: str = "pointer") -> tuple | None:
        """The answer after ``previous``; nothing but the links and that answer is used."""
        return next(self.walks(after=list(previous), compact=method == "pointer"), None)


def per_run(layers: Layers, body, schema: str, in_edges: bool = False, answers: AnswerEdges | None = None) -> DataFrame:
    """``body(emitter, target)`` yields rows; one task serves one run, and only links that lie on its answers go there
    (with ``in_edges`` also all edges into the vertices on answers, for the forms that browse them)."""
    nfa, alphabet = layers.nfa, layers.alphabet
    columns = ["level", "dst", "edge_id", "src", "lab", "src_mask", "dst_mask"]
    names = [c.split()[0] for c in schema.split(", ")]
    answers = answers or answer_edges(layers)
    links = answer_links(layers, answers)
    every = links.select("run_id", *columns, F.lit(True).alias("used"))
    if in_edges:
        met = answers.rows.select("run_id", F.col("vertex").alias("dst")).distinct()
        blank = layers.edges.select("edge_id", "dst").join(met, "dst").select("run_id", "dst", "edge_id")
        every = every.unionByName(blank.withColumn("used", F.lit(False)), allowMissingColumns=True)

    def run(rows: pd.DataFrame, ends: pd.DataFrame) -> pd.DataFrame:
        into = defaultdict(list)
        for edge, dst, used in zip(rows["edge_id"], rows["dst"], rows["used"]):
            if not used:
                into[dst].append(edge)
        used = rows[rows["used"].astype(bool)]
        found = [(int(a), b, c, d, int(e), int(f), int(g)) for a, b, c, d, e, f, g in used[columns].itertuples(index=False, name=None)]
        out = []
        for target, level, mask in ends[["target", "level", "mask"]].itertuples(index=False, name=None):
            out += body(Emitter(nfa, alphabet, found, target, int(level), int(mask), {k: sorted(v) for k, v in into.items()}), target)
        return pd.DataFrame(out, columns=names)

    return every.groupBy("run_id").cogroup(layers.ends.groupBy("run_id")).applyInPandas(run, schema)


def text(path) -> str:
    return ">".join(map(str, path))


def emit_local(layers: Layers, *, limit: int | None = None, compact: bool = True, merge: str = "heads", answers: AnswerEdges | None = None) -> DataFrame:
    """rank, edge_path and steps since the walk before, in order; stops after ``limit`` walks."""

    def body(emitter: Emitter, target):
        last = 0
        for rank, path in enumerate(emitter.walks(compact, merge)):
            if limit is not None and rank >= limit:
                return
            yield rank, text(path), emitter.steps - last
            last = emitter.steps

    return per_run(layers, body, "rank long, edge_path string, steps long", in_edges=not compact, answers=answers)


def walk_deltas(layers: Layers) -> DataFrame:
    """rank, kept (edges shared with the walk before, at the target's end) and the new edges."""

    def body(emitter: Emitter, target):
        last: tuple = ()
        for rank, path in enumerate(emitter.walks()):
            kept = 0
            while kept < min(len(path), len(last)) and path[-1 - kept] == last[-1 - kept]:
                kept += 1
            yield rank, kept, text(path[: len(path) - kept])
            last = path

    return per_run(layers, body, "rank long, kept long, new_edges string")


def iterate_next(layers: Layers, method: str, limit: int | None = None) -> DataFrame:
    """The walks found by asking for the next one again and again, with the steps of each question; stops after ``limit`` walks."""

    def body(emitter: Emitter, target):
        path, rank = next(emitter.walks(), None), 0
        while path is not None and (limit is None or rank < limit):
            yield rank, text(path), emitter.steps
            emitter.steps = 0
            path, rank = (emitter.next_walk(path, method) if path else None), rank + 1

    return per_run(layers, body, "rank long, edge_path string, steps long", in_edges=method == "scan")


def resumable(links: DataFrame) -> DataFrame:
    """Per-state links in in-edge order, each with the next edge that has a link for the state."""
    from pyspark.sql import Window as W

    states = links.select("*", F.explode(F.sequence(F.lit(0), F.lit(61))).alias("state")).where(F.col("dst_mask").bitwiseAND(F.expr("shiftleft(1L, state)")) != 0)
    order = W.partitionBy("run_id", "level", "dst", "state").orderBy("edge_id")
    return states.select("run_id", "level", "dst", "state", "edge_id", "src", F.lead("edge_id").over(order).alias("next_edge"))
