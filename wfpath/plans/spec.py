"""Workflow specifications: rules that rewrite a composite module into a small DAG of modules.

Everything here is as large as the specification and lives on the driver; ``to_tables`` mirrors it
as DataFrames.  Productions are numbered from 1 in the order given, positions of a body from 1.
"""

from __future__ import annotations

import hashlib
import random
from collections.abc import Iterable
from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


class BadSpec(ValueError):
    """The rules are no valid specification; the message says why."""


@dataclass(frozen=True)
class Production:
    """``lhs`` becomes the modules ``body`` (position 1 first), joined by edges (from, to, tag)."""

    number: int
    lhs: str
    body: tuple[str, ...]
    edges: tuple[tuple[int, int, str], ...]

    @cached_property
    def order(self) -> list[int]:
        """Positions in a topological order."""
        waiting = {i: 0 for i in range(1, len(self.body) + 1)}
        for _, v, _ in self.edges:
            waiting[v] += 1
        ready, found = [i for i, n in waiting.items() if n == 0], []
        while ready:
            u = ready.pop(0)
            found.append(u)
            for a, v, _ in self.edges:
                if a == u:
                    waiting[v] -= 1
                    if waiting[v] == 0:
                        ready.append(v)
        return found

    @cached_property
    def source(self) -> int:
        return self.order[0]

    @cached_property
    def sink(self) -> int:
        return self.order[-1]

    @cached_property
    def reach(self) -> set[tuple[int, int]]:
        """Pairs of different positions joined by a path."""
        found: set[tuple[int, int]] = set()
        for u in reversed(self.order):
            for a, v, _ in self.edges:
                if a == u:
                    found |= {(u, v)} | {(u, w) for x, w in found if x == v}
        return found


@dataclass(frozen=True)
class Cycle:
    """A cycle of the production graph: its modules, and for each the production and position that go on."""

    number: int
    modules: tuple[str, ...]
    slots: tuple[tuple[int, int], ...]


@dataclass(frozen=True)
class Spec:
    start: str
    productions: tuple[Production, ...]
    extra_tags: frozenset[str] = field(default=frozenset())

    @staticmethod
    def build(start: str, rules: Iterable[tuple[str, Iterable[str], Iterable[tuple]]]) -> Spec:
        """Rules are (module, body, edges); an edge is (from, to) or (from, to, tag), the tag being the source module's name by default."""
        made = []
        for number, (lhs, body, edges) in enumerate(rules, 1):
            body = tuple(body)
            if number >= 1 << 16 or len(body) >= 1 << 16:
                raise BadSpec("labels hold productions and positions in two bytes")
            if not body:
                raise BadSpec(f"production {number} of {lhs} has an empty body")
            full = []
            for u, v, *tag in edges:
                if not (1 <= u <= len(body) and 1 <= v <= len(body)):
                    raise BadSpec(f"production {number} has an edge {u}-{v} outside its body")
                full.append((u, v, tag[0] if tag else body[u - 1]))
            p = Production(number, lhs, body, tuple(full))
            if len(p.order) < len(body):
                raise BadSpec(f"the body of production {number} has a cycle")
            heads, tails = {v for _, v, _ in full}, {u for u, _, _ in full}
            if sum(i not in heads for i in range(1, len(body) + 1)) != 1 or sum(i not in tails for i in range(1, len(body) + 1)) != 1:
                raise BadSpec(f"the body of production {number} needs one source and one sink")
            made.append(p)
        spec = Spec(start, tuple(made))
        if start not in spec.composite:
            raise BadSpec(f"the start module {start} has no production")
        return spec

    @staticmethod
    def chain(start: str, rules: Iterable[tuple[str, str]]) -> Spec:
        """Rules whose bodies are written as ``a b {c d} e``: stages in a row, braces hold parallel modules."""
        full = []
        for lhs, text in rules:
            stages, inside = [], None
            for word in text.replace("{", " { ").replace("}", " } ").split():
                if word == "{":
                    inside = []
                elif word == "}":
                    stages.append(inside)
                    inside = None
                elif inside is not None:
                    inside.append(word)
                else:
                    stages.append([word])
            body = [m for s in stages for m in s]
            at, places = 1, []
            for s in stages:
                places.append(range(at, at + len(s)))
                at += len(s)
            full.append((lhs, body, [(u, v) for a, b in zip(places, places[1:], strict=False) for u in a for v in b]))
        return Spec.build(start, full)

    @cached_property
    def composite(self) -> frozenset[str]:
        return frozenset(p.lhs for p in self.productions)

    @cached_property
    def modules(self) -> frozenset[str]:
        return self.composite | {m for p in self.productions for m in p.body}

    @cached_property
    def tags(self) -> tuple[str, ...]:
        return tuple(sorted({t for p in self.productions for _, _, t in p.edges} | self.extra_tags))

    @cached_property
    def fingerprint(self) -> str:
        return hashlib.sha256(repr((self.start, self.productions, self.tags)).encode()).hexdigest()

    def atoms_at(self, tags: Iterable[str], end: str) -> frozenset[str]:
        """Atomic modules at which edges of these tags begin (end: src) or end (dst)."""
        wanted, found, seen = set(tags), set(), set()
        todo = [p.body[(u if end == "src" else v) - 1] for p in self.productions for u, v, t in p.edges if t in wanted]
        while todo:
            m = todo.pop()
            if m in seen:
                continue
            seen.add(m)
            if m in self.composite:
                # an edge out of a composite module leaves its sink, and one into it enters its source
                todo += [p.body[(p.sink if end == "src" else p.source) - 1] for p in self.of(m)]
            else:
                found.add(m)
        return frozenset(found)

    def of(self, module: str) -> list[Production]:
        return [p for p in self.productions if p.lhs == module]

    def __getitem__(self, number: int) -> Production:
        return self.productions[number - 1]

    @cached_property
    def size(self) -> int:
        """One for each production and for each module of its body."""
        return sum(1 + len(p.body) for p in self.productions)

    @cached_property
    def _links(self) -> dict[str, list[tuple[str, int, int]]]:
        """The production graph: module -> (module, production, position), parallel edges kept."""
        found: dict[str, list] = {m: [] for m in self.composite}
        for p in self.productions:
            for i, m in enumerate(p.body, 1):
                if m in self.composite:
                    found[p.lhs].append((m, p.number, i))
        return found

    def _reachable(self, module: str) -> set[str]:
        seen, todo = set(), [module]
        while todo:
            for m, _, _ in self._links[todo.pop()]:
                if m not in seen:
                    seen.add(m)
                    todo.append(m)
        return seen

    @cached_property
    def cycles(self) -> tuple[Cycle, ...]:
        """The vertex-disjoint cycles of a strictly linear recursive specification; else ``BadSpec``."""
        recursive = sorted(m for m in self.composite if m in self._reachable(m))
        done, found = set(), []
        # a cycle begins at its first module in rule order, so numbers don't depend on names
        rank = {m: min(p.number for p in self.of(m)) for m in recursive}
        for m in sorted(recursive, key=rank.__getitem__):
            if m in done:
                continue
            modules, slots, at = [], [], m
            while True:
                onward = [x for x in self._links[at] if m in self._reachable(x[0]) | {x[0]} and at in self._reachable(x[0]) | {x[0]}]
                if len(onward) != 1:
                    raise BadSpec(f"not strictly linear: {len(onward)} recursive places continue from {at}")
                modules.append(at)
                slots.append(onward[0][1:])
                at = onward[0][0]
                if at == m:
                    break
                if at in modules:
                    raise BadSpec(f"not strictly linear: cycles share the module {at}")
            done |= set(modules)
            found.append(Cycle(len(found) + 1, tuple(modules), tuple(slots)))
        return tuple(found)

    def is_strictly_linear(self) -> bool:
        try:
            return self.cycles is not None
        except BadSpec:
            return False

    @cached_property
    def place(self) -> dict[str, tuple[int, int]]:
        """Recursive module -> (cycle, offset from 1 of its place there)."""
        return {m: (c.number, t) for c in self.cycles for t, m in enumerate(c.modules, 1)}

    def colour(self, number: int, position: int) -> str | None:
        """'red' if the position leads to the production's recursive slot, 'blue' if the slot leads to it."""
        slot = next((i for c in self.cycles for k, i in c.slots if k == number), None)
        if slot is None or slot == position:
            return None
        reach = self[number].reach
        return "red" if (position, slot) in reach else "blue" if (slot, position) in reach else None

    @cached_property
    def statistics(self) -> dict[str, int]:
        slots = {k for c in self.cycles for k, _ in c.slots}
        return {"size": self.size, "modules": len(self.modules), "composite": len(self.composite), "productions": len(self.productions), "recursive": len(slots)}


TABLES = {
    "spec_module": T.StructType([T.StructField("name", T.StringType()), T.StructField("composite", T.BooleanType())]),
    "spec_production": T.StructType([T.StructField("k", T.IntegerType()), T.StructField("lhs", T.StringType())]),
    "spec_body_node": T.StructType([T.StructField("k", T.IntegerType()), T.StructField("pos", T.IntegerType()), T.StructField("module", T.StringType())]),
    "spec_body_edge": T.StructType([T.StructField("k", T.IntegerType()), T.StructField("src_pos", T.IntegerType()), T.StructField("dst_pos", T.IntegerType()), T.StructField("tag", T.StringType())]),
}


def to_tables(spec: Spec, spark: SparkSession) -> dict[str, DataFrame]:
    rows = {
        "spec_module": [(m, m in spec.composite) for m in sorted(spec.modules)],
        "spec_production": [(p.number, p.lhs) for p in spec.productions],
        "spec_body_node": [(p.number, i, m) for p in spec.productions for i, m in enumerate(p.body, 1)],
        "spec_body_edge": [(p.number, u, v, t) for p in spec.productions for u, v, t in p.edges],
    }
    return {k: spark.createDataFrame(v, TABLES[k]) for k, v in rows.items()}


def from_tables(tables: dict[str, DataFrame], start: str) -> Spec:
    """The tables are as small as the specification."""
    got = {k: [tuple(r) for r in tables[k].collect()] for k in ("spec_production", "spec_body_node", "spec_body_edge")}
    rules = []
    for k, lhs in sorted(got["spec_production"]):
        body = [m for _, _, m in sorted(x for x in got["spec_body_node"] if x[0] == k)]
        rules.append((lhs, body, [(u, v, t) for n, u, v, t in got["spec_body_edge"] if n == k]))
    return Spec.build(start, rules)


def random_spec(size: int, n_cycles: int = 3, cycle_len: int = 1, degree: int = 2, seed: int = 0) -> Spec:
    """A strictly linear specification of about ``size``: a tree of composite modules, some of which recur."""
    rng = random.Random(seed)
    rules, atoms, total = [], 0, 0

    def atom() -> str:
        nonlocal atoms
        atoms += 1
        return f"a{atoms}"

    def body(inner: list[str], length: int):
        """A DAG with one source and one sink: every position hangs on up to ``degree`` earlier ones."""
        nodes = [atom(), *rng.sample(inner + [atom() for _ in range(max(0, length - len(inner)))], max(len(inner), length)), atom()]
        n, edges = len(nodes), set()
        for v in range(2, n):
            edges |= {(u, v) for u in rng.sample(range(1, v), min(v - 1, rng.randint(1, degree)))}
        for u in range(1, n):
            if not any(a == u for a, _ in edges):
                edges.add((u, n))
        if not any(v == n for _, v in edges):
            edges.add((n - 1, n))
        return nodes, sorted(edges)

    waiting, made, cycles = ["M0"], 1, 0
    while waiting:
        m = waiting.pop(0)
        room = size - total > 12 * (len(waiting) + 1)
        children = []
        for _ in range(rng.randint(1, 2) if room else 0):
            children.append(f"M{made}")
            made += 1
        if cycles < n_cycles and m != "M0":
            cycles += 1
            ring = [m] + [f"{m}r{j}" for j in range(1, cycle_len)]
            for j, x in enumerate(ring):
                nodes, edges = body([ring[(j + 1) % cycle_len], *(children if j == 0 else [])], rng.randint(1, 3))
                rules.append((x, nodes, edges))
                rules.append((x, *body([], rng.randint(1, 3))))
        else:
            rules.append((m, *body(children, rng.randint(2, 5))))
            if m != "M0" and rng.random() < 0.4:
                rules.append((m, *body([], rng.randint(1, 4))))
        waiting += children
        total = sum(1 + len(b) for _, b, _ in rules)
        if not waiting and total < size - 12:
            # hang another subtree on the start
            lhs, nodes, edges = rules[0]
            new = f"M{made}"
            made += 1
            n = len(nodes)
            shifted = [(u if u < n else n + 1, v if v < n else n + 1) for u, v in edges]
            rules[0] = (lhs, [*nodes[:-1], new, nodes[-1]], sorted({*shifted, (1, n), (n, n + 1)}))
            waiting.append(new)
    return Spec.build("M0", rules)


def _shaped(size: int, modules: int, composite: int, productions: int, recursive: int, deep: bool, seed: int, fork: bool = False) -> Spec:
    """A specification with exactly these statistics; ``deep`` nests its composite modules, else they stand side by side.

    With ``fork`` the innermost recursion of a deep one is a fork: its next member stands beside the rest of the body.
    """
    rng = random.Random(seed)
    names = [f"{'D' if deep else 'B'}{i}" for i in range(composite)]
    inner: dict[int, list[str]] = {i: [] for i in range(composite)}
    for i in range(1, composite):
        inner[i - 1 if deep else (i - 1) // 4].append(names[i])
    # rule list: a first rule for each module holds its children; recursive modules get a recursive and an ending rule
    looped = names[1 : recursive + 1]
    # with too few productions for an ending each, two recursive modules share a cycle and one ending
    twin = composite + recursive > productions
    onward = dict(zip(looped, looped, strict=True)) | ({looped[0]: looped[1], looped[1]: looped[0]} if twin else {})
    if twin:
        inner[names.index(looped[0])] = [m for m in inner[names.index(looped[0])] if m != looped[1]]
        for m in inner.values():
            if looped[1] in m:
                m.remove(looped[1])
    plan = [(n, [*inner[i], *([onward[n]] if n in looped else [])]) for i, n in enumerate(names)]
    plan += [(n, []) for n in looped if not (twin and n == looped[1])]
    spare = [n for n in names[recursive + 1 :]]
    j = 0
    while len(plan) < productions:
        plan.append((spare[j % len(spare)], []))
        j += 1
    lengths = [len(b) + 2 for _, b in plan]
    left = size - len(plan) - sum(lengths)
    while left > 0:
        lengths[rng.randrange(len(lengths))] += 1
        left -= 1
    # the number of atomic places is what is left of the bodies; names repeat until the count of modules is met
    places = sum(n - len(b) for n, (_, b) in zip(lengths, plan, strict=True))
    pool = [f"t{i}" for i in range(modules - composite)]
    word = (pool * (places // len(pool) + 1))[:places]
    rules, at = [], 0
    for n, (lhs, b) in zip(lengths, plan, strict=True):
        own = word[at : at + n - len(b)]
        at += len(own)
        nodes = [own[0], *b, *own[1:]]
        if deep and not (fork and lhs == looped[-1] and onward[lhs] in b):
            edges = [(i, i + 1) for i in range(1, n)]
        else:
            middle = range(2, n)
            edges = [(1, i) for i in middle] + [(i, n) for i in middle] if n > 2 else [(1, 2)]
        rules.append((lhs, nodes, edges))
    return Spec.build(names[0], rules)


#: Size, modules, composite modules, productions and recursive productions of the two workflows.
DEEP, BRANCHY = (166, 112, 16, 23, 7), (105, 77, 11, 15, 5)


def deep_like(seed: int = 0, fork: bool = False) -> Spec:
    return _shaped(*DEEP, deep=True, seed=seed, fork=fork)


def branchy_like(seed: int = 0) -> Spec:
    return _shaped(*BRANCHY, deep=False, seed=seed)


def fork_tags(spec: Spec) -> list[str]:
    """Tags whose star follows a chain: they lead into the recursive slot of a production whose head is an atomic module."""
    slots = {(k, i) for c in spec.cycles for k, i in c.slots}
    found = []
    for p in spec.productions:
        heads = [t for u, v, t in p.edges if (p.number, v) in slots and u == p.source and p.body[u - 1] not in spec.composite]
        found += [t for t in heads if t not in found]
    return found
