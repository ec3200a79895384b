"""Labels of run nodes as columns: packing, prefixes, levels, state masks, and the pair decision.

A label is an array of entries (kind, a, b, idx): kind 0 is position b of production a; kind 1 is
member idx of a chain that entered cycle a at offset b.  ``pack`` gives bytes whose order is tree
order and whose prefixes are label prefixes.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wfpath.plans.rpq import Dfa
from wfpath.plans.safety import Relation, SafePlan
from wfpath.plans.spec import Spec

ENTRY = "struct<kind:tinyint,a:int,b:int,idx:bigint>"
LABEL = f"array<{ENTRY}>"
WIDTH = 10


def entry(kind: int, a: int | Column, b: int | Column, idx: int | Column = 0) -> Column:
    as_col = lambda x: x if isinstance(x, Column) else F.lit(x)
    return F.struct(F.lit(kind).cast("tinyint").alias("kind"), as_col(a).cast("int").alias("a"), as_col(b).cast("int").alias("b"), as_col(idx).cast("bigint").alias("idx"))


def pos(k: int | Column, i: int | Column) -> Column:
    return entry(0, k, i)


def member(cycle: int, offset: int | Column, idx: Column) -> Column:
    return entry(1, cycle, offset, idx)


def pack(label: Column) -> Column:
    """Ten bytes an entry: kind, a, b, idx, big-endian; an entry that needs more raises an error."""
    def wide(x: Column, n: int) -> Column:
        digits = F.hex(x.cast("bigint"))
        return F.when(F.length(digits) <= n, F.lpad(digits, n, "0")).otherwise(F.raise_error(F.lit("an entry is too large to pack")).cast("string"))

    return F.unhex(F.array_join(F.transform(label, lambda e: F.concat(wide(e["kind"], 2), wide(e["a"], 4), wide(e["b"], 4), wide(e["idx"], 10))), ""))


def unpack(key: Column) -> Column:
    """The label of packed bytes."""
    def part(at: Column, begin: int, size: int) -> Column:
        return F.conv(F.hex(F.substring(key, at * WIDTH + 1 + begin, F.lit(size))), 16, 10).cast("bigint")

    n = (F.length(key) / WIDTH).cast("int")
    steps = F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(steps, lambda i: F.struct(part(i, 0, 1).cast("tinyint").alias("kind"), part(i, 1, 2).cast("int").alias("a"), part(i, 3, 2).cast("int").alias("b"), part(i, 5, 5).alias("idx")))


def prefix(key: Column, depth: Column | int) -> Column:
    """The packed prefix of so many entries."""
    return F.substring(key, F.lit(1), (depth if isinstance(depth, Column) else F.lit(depth)) * WIDTH)


def constants(values: list[int]) -> Column:
    """An array of numbers as one folded literal, however long."""
    return F.split(F.lit(",".join(map(str, values)) or "0"), ",").cast("array<bigint>")


def bound(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a value that is computed once, however often the body names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def _any_of(masks: list[Column]) -> Column:
    return reduce(lambda x, y: x.bitwiseOR(y), masks)


class Lookup:
    """Relations by number as one literal: row q of relation r is element r * states + q."""

    def __init__(self, states: int) -> None:
        self.states, self.flat = states, []

    def add(self, r: Relation) -> int:
        self.flat += r
        return len(self.flat) // self.states - 1

    def rows(self) -> Column:
        return constants(self.flat)

    def _bits(self) -> list[tuple[int, Column]]:
        return [(q, F.lit(1 << q).cast("bigint")) for q in range(self.states)]

    def forward(self, mask: Column, number: Column) -> Column:
        """States after the relation, from the states of a mask."""
        rows, none = self.rows(), F.lit(0).cast("bigint")
        own = lambda m, at: _any_of([F.when(m.bitwiseAND(bit) != 0, F.get(rows, at + q)).otherwise(none) for q, bit in self._bits()])
        return bound(mask, lambda m: bound((number * self.states).cast("int"), lambda at: own(m, at)))

    def backward(self, mask: Column, number: Column) -> Column:
        """States from which the relation leads into the mask."""
        rows, none = self.rows(), F.lit(0).cast("bigint")
        own = lambda m, at: _any_of([F.when(F.get(rows, at + q).bitwiseAND(m) != 0, bit).otherwise(none) for q, bit in self._bits()])
        return bound(mask, lambda m: bound((number * self.states).cast("int"), lambda at: own(m, at)))


class Decoder:
    """A safe plan's tables as literals of a few kilobytes, and the columns that use them."""

    def __init__(self, plan: SafePlan) -> None:
        self.plan, spec, n = plan, plan.spec, plan.dfa.n
        if n > 62:
            raise ValueError("the column kernel holds states in 62 bits; use the array kernel for more")
        self.enter, self.leave, self.between = Lookup(n), Lookup(n), Lookup(n)
        self.first, self.width, self.pair_first = [0], [0], [0]
        for p in spec.productions:
            body, size = plan.bodies[p.number], len(p.body)
            self.first.append(len(self.enter.flat) // n)
            self.width.append(size)
            self.pair_first.append(len(self.between.flat) // n)
            for i in range(1, size + 1):
                self.enter.add(body.enter[i])
                self.leave.add(body.leave[i])
            for i in range(1, size + 1):
                for j in range(1, size + 1):
                    self.between.add(body.between.get((i, j), (0,) * n))
        # powers by cycle and phase: where they begin, and when they begin to repeat
        longest = max([1, *(len(c.modules) for c in spec.cycles)])
        self.longest, self.power, self.cells = longest, {}, {}
        for way, table in (("enter", self.enter), ("leave", self.leave)):
            base = len(table.flat) // n
            for r in plan.powers.rows[way]:
                table.add(r)
            cells = [(0, 1, 1)] * ((len(spec.cycles) + 1) * longest)
            for (c, phase, w), (at, before, period) in plan.powers.index.items():
                if w == way:
                    cells[c * longest + phase] = (base + at, before, period)
            self.cells[way] = cells
            self.power[way] = [constants([x[k] for x in cells]) for k in range(3)]
        slot = {k: i for c in spec.cycles for k, i in c.slots}
        self.cycles = [1, *(len(c.modules) for c in spec.cycles)], [0, *(slot.get(p.number, 0) for p in spec.productions)]
        self.lengths, self.slots = map(constants, self.cycles)
        self.final, self.accepts_empty = plan.dfa.final_mask, 0 in plan.dfa.finals

    def _at(self, numbers: list[int], k: Column) -> Column:
        return F.get(constants(numbers), k.cast("int"))

    def steps(self, way: str, cycle: Column, phase: Column, count: Column) -> Column:
        """Number of the relation of ``count`` slots of a cycle."""
        cell = (cycle * self.longest + phase).cast("int")
        base, before, period = (F.get(x, cell) for x in self.power[way])
        return base + F.when(count < before + period, count).otherwise(before + (count - before) % period)

    def length(self, cycle: Column) -> Column:
        return F.get(self.lengths, cycle.cast("int"))

    def down(self, e: Column) -> Column:
        """Number of the relation from into an ancestor to into the node that entry e names."""
        return F.when(e["kind"] == 0, self._at(self.first, e["a"]) + e["b"] - 1).otherwise(self.steps("enter", e["a"], (e["b"] - 1).cast("bigint"), e["idx"] - 1))

    def up(self, e: Column) -> Column:
        """Number of the relation from out of the node that entry e names to out of its ancestor."""
        n = self.length(e["a"])
        phase = (e["b"] - 1 + e["idx"] - 2 + n) % n
        return F.when(e["kind"] == 0, self._at(self.first, e["a"]) + e["b"] - 1).otherwise(self.steps("leave", e["a"], phase, e["idx"] - 1))

    def pair(self, k: Column, i: Column, j: Column) -> Column:
        return self._at(self.pair_first, k) + (i - 1) * self._at(self.width, k) + j - 1

    def exits(self, label: Column) -> Column:
        """For each depth d: the states on leaving the ancestor that the first d + 1 entries name."""
        begin = F.array(F.lit(1).cast("bigint"))
        rest = F.reverse(F.slice(label, F.lit(2), F.size(label)))
        return F.reverse(F.aggregate(rest, begin, lambda acc, e: F.concat(acc, F.array(self.leave.forward(F.element_at(acc, -1), self.up(e))))))

    def entries(self, label: Column) -> Column:
        """For each depth d: the states on entering that ancestor from which the node can be reached accepting."""
        begin = F.array(F.lit(self.final).cast("bigint"))
        rest = F.reverse(F.slice(label, F.lit(2), F.size(label)))
        return F.reverse(F.aggregate(rest, begin, lambda acc, e: F.concat(acc, F.array(self.enter.backward(F.element_at(acc, -1), self.down(e))))))

    def same_body(self, exit_mask: Column, k: Column, i: Column, j: Column) -> Column:
        return self.between.forward(exit_mask, self.pair(k, i, j))

    def holds(self, u: dict[str, Column], v: dict[str, Column]) -> Column:
        """Whether the path exists, from labels and masks of both nodes (keys label, exits and entries)."""
        lu, lv = u["label"], v["label"]
        depth = F.array_position(F.zip_with(lu, lv, lambda x, y: F.when(x.eqNullSafe(y), 0).otherwise(1)), 1).cast("int") - 1

        def at(d: Column) -> Column:
            places = {"x": (lu, d), "y": (lv, d), "nx": (lu, d + 1), "ny": (lv, d + 1), "eu": (u["exits"], d), "eu1": (u["exits"], d + 1), "ev": (v["entries"], d), "ev1": (v["entries"], d + 1)}
            return F.struct(*[F.get(array, i).alias(name) for name, (array, i) in places.items()])

        return bound(depth, lambda d: F.when(d < 0, F.lit(self.accepts_empty)).otherwise(bound(at(d), self._met)))

    def _met(self, r: Column) -> Column:
        """The decision where two labels part: entries x and y, the next ones, and the masks at both depths."""
        x, y, nx, ny = r["x"], r["y"], r["nx"], r["ny"]
        n, s, t = self.length(x["a"]), x["a"], x["b"] - 1
        body = self.same_body(r["eu"], x["a"], x["b"], y["b"]).bitwiseAND(r["ev"])
        onward = self.same_body(r["eu1"], nx["a"], nx["b"], F.get(self.slots, nx["a"]))
        onward = self.enter.forward(onward, self.steps("enter", s, (t + x["idx"]) % n, y["idx"] - 1 - x["idx"])).bitwiseAND(r["ev"])
        back = self.leave.forward(r["eu"], self.steps("leave", s, (t + x["idx"] - 2 + n) % n, x["idx"] - 1 - y["idx"]))
        back = self.same_body(back, ny["a"], F.get(self.slots, ny["a"]), ny["b"]).bitwiseAND(r["ev1"])
        same_place = (x["kind"] == y["kind"]) & (x["a"] == y["a"])
        met = F.when(~same_place, 0).when(x["kind"] == 0, body).when(x["b"] != y["b"], 0).when(x["idx"] < y["idx"], onward).otherwise(back)
        return F.coalesce(met != 0, F.lit(False))


def reach_table(spec: Spec) -> tuple[list[int], list[int], list[int]]:
    """Reachability between positions: where a production's square begins, its width, and the flat squares."""
    first, width, flat = [0], [0], []
    for p in spec.productions:
        first.append(len(flat))
        width.append(len(p.body))
        flat += [int((i, j) in p.reach) for i in range(1, len(p.body) + 1) for j in range(1, len(p.body) + 1)]
    return first, width, flat


def body_reaches(spec: Spec, k: Column, i: Column, j: Column) -> Column:
    first, width, flat = map(constants, reach_table(spec))
    return F.get(flat, (F.get(first, k.cast("int")) + (i - 1) * F.get(width, k.cast("int")) + j - 1).cast("int")) == 1


def levels(nodes: DataFrame, spec: Spec) -> DataFrame:
    """One row for each ancestor of each node: depth, packed prefix, entry, next entry, colour of the next entry."""
    colours = {(p.number, i): spec.colour(p.number, i) for p in spec.productions for i in range(1, len(p.body) + 1)}
    red = [(k << 16) + i for (k, i), c in colours.items() if c == "red"]
    blue = [(k << 16) + i for (k, i), c in colours.items() if c == "blue"]
    x = nodes.withColumn("_key", pack(F.col("label")))
    x = x.select("*", F.posexplode("label").alias("depth", "entry"))
    x = x.withColumn("prefix", prefix(F.col("_key"), F.col("depth"))).withColumn("onward", F.get("label", F.col("depth") + 1)).drop("_key")
    code = F.col("onward.a").cast("bigint") * (1 << 16) + F.col("onward.b")
    return x.withColumn("colour", F.when(code.isin(red), "red").when(code.isin(blue), "blue") if red or blue else F.lit(None).cast("string"))


def array_kernel(plan: SafePlan) -> Callable:
    """A pandas UDF (label, label) -> boolean for any number of states; Python integers hold the masks."""
    spec, dfa = plan.spec, plan.dfa
    slot = {k: i for c in spec.cycles for k, i in c.slots}
    length = {c.number: len(c.modules) for c in spec.cycles}
    final, empty = dfa.final_mask, 0 in dfa.finals
    from wfpath.plans.safety import image

    def relation(e, way: str) -> Relation:
        if e["kind"] == 0:
            return getattr(plan.bodies[e["a"]], way)[e["b"]]
        n = length[e["a"]]
        return plan.powers.get(e["a"], (e["b"] - 1) % n if way == "enter" else (e["b"] + e["idx"] - 3) % n, e["idx"] - 1, way)

    def before(mask: int, r: Relation) -> int:
        return sum(1 << q for q, row in enumerate(r) if row & mask)

    def masks(label, way: str) -> list[int]:
        out = [1 if way == "leave" else final]
        for e in label[:0:-1]:
            r = relation(e, way)
            out.append(image(out[-1], r) if way == "leave" else before(out[-1], r))
        return out[::-1]

    def decide(lu, lv) -> bool:
        d = next((i for i, (x, y) in enumerate(zip(lu, lv, strict=False)) if x != y), None)
        if d is None:
            return empty and len(lu) == len(lv)
        x, y = lu[d], lv[d]
        if x["kind"] != y["kind"] or x["a"] != y["a"]:
            return False
        none: Relation = (0,) * dfa.n
        if x["kind"] == 0:
            return bool(image(masks(lu, "leave")[d], plan.bodies[x["a"]].between.get((x["b"], y["b"]), none)) & masks(lv, "enter")[d])
        if x["b"] != y["b"]:
            return False
        n, i, j, t = length[x["a"]], x["idx"], y["idx"], x["b"] - 1
        if i < j:
            k = lu[d + 1]
            now = image(masks(lu, "leave")[d + 1], plan.bodies[k["a"]].between.get((k["b"], slot.get(k["a"], 0)), none))
            return bool(image(now, plan.powers.get(x["a"], (t + i) % n, j - 1 - i, "enter")) & masks(lv, "enter")[d])
        k = lv[d + 1]
        now = image(masks(lu, "leave")[d], plan.powers.get(x["a"], (t + i - 2) % n, i - 1 - j, "leave"))
        return bool(image(now, plan.bodies[k["a"]].between.get((slot.get(k["a"], 0), k["b"]), none)) & masks(lv, "enter")[d + 1])

    @F.pandas_udf("boolean")
    def rpq_holds(left: pd.Series, right: pd.Series) -> pd.Series:
        plain = lambda label: [{k: int(e[k]) for k in ("kind", "a", "b", "idx")} for e in label]
        return pd.Series(np.fromiter((decide(plain(a), plain(b)) for a, b in zip(left, right, strict=True)), bool, len(left)))

    return rpq_holds


def label_bits(spec: Spec, longest_chain: int) -> Column:
    """Bits of a label if every entry takes what its kind needs."""
    place = max(1, int(np.ceil(np.log2(1 + sum(len(p.body) for p in spec.productions)))))
    chain = max(1, int(np.ceil(np.log2(1 + longest_chain))))
    return F.aggregate("label", F.lit(0), lambda acc, e: acc + F.when(e["kind"] == 0, place).otherwise(place + chain))


__all__ = ["Decoder", "Dfa", "array_kernel", "body_reaches", "label_bits", "levels", "member", "pack", "pos", "prefix", "unpack"]
