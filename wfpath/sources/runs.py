"""Runs of workflow specifications derived from the tables.

Each carrier has a specification, labelled nodes by window functions, and edges by SQL that never
looks at labels and that Spark and DuckDB both read.  A run is a user, source, customer,
conversation, the world, or a host.
"""

from __future__ import annotations

import functools
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from wfpath.functions.labels import LABEL, member, pos
from wfpath.plans.spec import Spec


@dataclass(frozen=True)
class RunData:
    """nodes (run_id, node_id, module, label), edges (run_id, src, dst, tag), and their specification."""

    nodes: DataFrame
    edges: DataFrame
    spec: Spec

    @property
    def places(self) -> DataFrame:
        """run_id, node_id of the nodes."""
        return self.nodes.select("run_id", "node_id")

    def part(self, modules: list[str]) -> DataFrame:
        """The nodes of some modules."""
        return self.nodes.where(F.col("module").isin(sorted(set(modules))))

    def tagged(self, tags: list[str]) -> DataFrame:
        """The edges of some tags."""
        return self.edges.where(F.col("tag").isin(sorted(set(tags))))


class StoredRun:
    """The same three of a run whose rows are written to a folder at their first use and read from there.

    Nodes keep their labels; edges lie in a folder for each tag.  A later query reads the columns,
    modules and tags that it needs instead of deriving the run again.
    """

    def __init__(self, run: Callable[[], RunData], spec: Spec, folder: str, some: Callable[[frozenset[str]], DataFrame] | None = None) -> None:
        self.spec, self._run, self._folder, self._written, self._some = spec, run, folder, set(), some

    def _rows(self, spark: SparkSession, kind: str, schema: str, write: Callable[[str], None]) -> DataFrame:
        if kind in self._written:
            try:
                return spark.read.schema(schema).parquet(f"{self._folder}/{kind}")
            except AnalysisException:  # the folder was cleaned meanwhile, with all that lay there
                self._written.clear()
                self._folder = f"{self._folder}x"
        path = f"{self._folder}/{kind}"
        write(path)
        self._written.add(kind)
        return spark.read.schema(schema).parquet(path)

    def _nodes(self, kind: str, rows: Callable[[], DataFrame]) -> DataFrame:
        columns = ["run_id", "node_id", "module", "label"]
        return self._rows(SparkSession.active(), kind, f"run_id string, node_id string, module string, label {LABEL}", lambda path: rows().select(*columns).write.parquet(path))

    @property
    def nodes(self) -> DataFrame:
        return self._nodes("nodes", lambda: self._run().nodes)

    def part(self, modules: list[str]) -> DataFrame:
        """The nodes of some modules.  If the run's nodes weren't written yet, only these are derived and written."""
        chosen = sorted(set(modules))
        if self._some is None or "nodes" in self._written:
            return self.nodes.where(F.col("module").isin(chosen))
        return self._nodes("nodes-" + "-".join(chosen), lambda: self._some(frozenset(chosen)))

    @property
    def places(self) -> DataFrame:
        """run_id, node_id of the nodes.  If these weren't written yet, they are derived without labels, and not written."""
        return (self.nodes if "nodes" in self._written else self._run().nodes).select("run_id", "node_id")

    @property
    def edges(self) -> DataFrame:
        return self._edges("edges", lambda: self._run().edges)

    def _edges(self, kind: str, rows: Callable[[], DataFrame]) -> DataFrame:
        return self._rows(SparkSession.active(), kind, "run_id string, src string, dst string, tag string", lambda path: write_index(rows(), path))

    def tagged(self, tags: list[str]) -> DataFrame:
        """The edges of some tags.  If the run's edges weren't written yet, only these are derived and written."""
        chosen = sorted(set(tags))
        some = F.col("tag").isin(chosen)
        if "edges" in self._written:
            return self.edges.where(some)
        return self._edges("edges-" + "-".join(chosen), lambda: self._run().edges.where(some))


def write_index(edges: DataFrame, path: str) -> None:
    """Edges in a folder for each tag, sorted by run: looking a tag up reads its folder only.

    Ranges of (tag, run, node) are cut by sampled sizes, so a common tag spreads over as many tasks as it needs.
    """
    edges.select("run_id", "src", "dst", "tag").repartitionByRange("tag", "run_id", "src").sortWithinPartitions("tag", "run_id").write.partitionBy("tag").parquet(path)


@dataclass(frozen=True)
class Carrier:
    name: str
    spec: Spec
    edges_sql: str
    nodes: Callable[[SparkSession, str], DataFrame]
    tables: tuple[str, ...]
    #: The nodes of some modules, where they can be derived without the others.
    some: Callable[[SparkSession, str, frozenset[str]], DataFrame] | None = None

    def build(self, spark: SparkSession, sf_dir: str) -> RunData:
        return RunData(self.nodes(spark, sf_dir), self.edges(spark, sf_dir), self.spec)

    def stored(self, spark: SparkSession, sf_dir: str, folder: str) -> StoredRun:
        some = None if self.some is None else lambda modules: self.some(SparkSession.active(), sf_dir, modules)
        return StoredRun(lambda: self.build(SparkSession.active(), sf_dir), self.spec, folder, some)

    def edges(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        frames = {t: table(spark, sf_dir, t) for t in self.tables}
        text = self.edges_sql.replace("{micros}", "unix_micros(CAST(ts AS TIMESTAMP))")
        return spark.sql(text, **frames)

    def duckdb(self) -> str:
        """The same edges for DuckDB over views named like the tables."""
        text = self.edges_sql.replace("{micros}", "epoch_us(ts)")
        for t in self.tables:
            text = text.replace("{" + t + "}", t)
        return text


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def atoms(rows: DataFrame, spec: Spec, k: Column, prefix_id: Column, prefix_label: list[Column], keep: tuple[str, ...] = (), only: frozenset[str] | None = None) -> DataFrame:
    """Nodes for the atomic positions of production ``k`` (a column) of each row, of some modules only if these are named."""
    cases = F.lit(None).cast("array<struct<pos:int,module:string>>")
    for p in spec.productions:
        own = [F.struct(F.lit(i).alias("pos"), F.lit(m).alias("module")) for i, m in enumerate(p.body, 1) if m not in spec.composite and (only is None or m in only)]
        if own:
            cases = F.when(F.col("_k") == p.number, F.array(*own)).otherwise(cases)
    x = rows.withColumn("_k", k).withColumn("_atom", F.explode(cases))
    label = F.concat(F.array(*prefix_label, pos(F.col("_k"), F.col("_atom.pos"))))
    return x.select("run_id", F.concat(prefix_id, F.lit("."), F.col("_atom.module")).alias("node_id"), F.col("_atom.module").alias("module"), label.alias("label"), *keep)


def _rank(by: list, order: list) -> tuple[Column, Column]:
    """Rank within a group, and whether the row is its last."""
    w = Window.partitionBy(*by).orderBy(*order)
    return F.row_number().over(w).cast("bigint"), F.lead(F.lit(1)).over(w).isNull()


# ---- E: sessions of events -------------------------------------------------------------------
GAP = 43_200_000_000
EVENTS = Spec.chain(
    "RUN",
    [
        ("RUN", "begin SESS end"), ("SESS", "VISIT SESS"), ("SESS", "VISIT"), ("VISIT", "arrive STEPS leave"), ("STEPS", "STEP STEPS"), ("STEPS", "STEP"),
        ("STEP", "click ack"), ("STEP", "view ack"), ("STEP", "signup verify ack"), ("STEP", "purchase {charge ship} ack"), ("STEP", "error retry ack"),
    ],
)
KINDS = {"click": 7, "view": 8, "signup": 9, "purchase": 10, "error": 11}


def events_ranked(events: DataFrame, gap: int = GAP) -> DataFrame:
    """run_id, event_type, a (session), b (event within it), and whether each is the last."""
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    x = events.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    x = x.withColumn("new", F.when(F.col("us") - F.lag("us").over(w) <= gap, 0).otherwise(1)).withColumn("a", F.sum("new").over(w).cast("bigint"))
    b, last_b = _rank(["user_id", "a"], ["us", "event_id"])
    last = F.max("a").over(Window.partitionBy("user_id"))
    return x.select(F.concat(F.lit("u"), F.col("user_id").cast("string")).alias("run_id"), "event_type", "value", "props", "a", b.alias("b"), last_b.alias("last_b"), (F.col("a") == last).alias("last_a"), "us")


def _events_nodes(spark: SparkSession, sf_dir: str, only: frozenset[str] | None = None) -> DataFrame:
    x = events_ranked(table(spark, sf_dir, "events"))
    run = x.select("run_id").distinct()
    ends = atoms(run, EVENTS, F.lit(1), F.col("run_id"), [], only=only)
    visit = [pos(1, 2), member(1, 1, F.col("a")), pos(F.when(F.col("last_a"), 3).otherwise(2), 1)]
    sessions = x.where("last_b")
    place = F.concat_ws(".", "run_id", F.concat(F.lit("s"), F.col("a").cast("string")))
    step = [*visit, pos(4, 2), member(2, 1, F.col("b")), pos(F.when(F.col("last_b"), 6).otherwise(5), 1)]
    kind = F.coalesce(*[F.when(F.col("event_type") == e, k) for e, k in KINDS.items()])
    steps = atoms(x, EVENTS, kind, F.concat(place, F.lit(".e"), F.col("b").cast("string")), step, only=only)
    return ends.union(atoms(sessions, EVENTS, F.lit(4), place, visit, only=only)).union(steps)


_EVENTS_SQL = """
WITH e AS (
  SELECT 'u' || CAST(user_id AS STRING) AS run_id, event_type, event_id, {micros} AS us FROM {events}),
g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY run_id ORDER BY us, event_id) <= 43200000000 THEN 0 ELSE 1 END AS fresh FROM e),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY run_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS a FROM g),
r AS (SELECT *, row_number() OVER (PARTITION BY run_id, a ORDER BY us, event_id) AS b FROM s),
p AS (SELECT *, run_id || '.s' || CAST(a AS STRING) AS v, run_id || '.s' || CAST(a AS STRING) || '.e' || CAST(b AS STRING) || '.' AS n FROM r),
q AS (
  SELECT *, lead(n || event_type) OVER (PARTITION BY run_id ORDER BY us, event_id) AS after, lead(v) OVER (PARTITION BY run_id ORDER BY us, event_id) AS next_v,
         lag(v) OVER (PARTITION BY run_id ORDER BY us, event_id) AS before_v FROM p)
SELECT run_id, run_id || '.begin' AS src, v || '.arrive' AS dst, 'begin' AS tag FROM q WHERE before_v IS NULL
UNION ALL SELECT run_id, v || '.arrive', n || event_type, 'arrive' FROM q WHERE before_v IS NULL OR before_v <> v
UNION ALL SELECT run_id, n || 'ack', after, 'STEP' FROM q WHERE next_v = v
UNION ALL SELECT run_id, n || 'ack', v || '.leave', 'STEPS' FROM q WHERE next_v IS NULL OR next_v <> v
UNION ALL SELECT run_id, v || '.leave', next_v || '.arrive', 'VISIT' FROM q WHERE next_v <> v
UNION ALL SELECT run_id, v || '.leave', run_id || '.end', 'SESS' FROM q WHERE next_v IS NULL
UNION ALL SELECT run_id, n || event_type, n || 'ack', event_type FROM q WHERE event_type IN ('click', 'view')
UNION ALL SELECT run_id, n || 'signup', n || 'verify', 'signup' FROM q WHERE event_type = 'signup'
UNION ALL SELECT run_id, n || 'verify', n || 'ack', 'verify' FROM q WHERE event_type = 'signup'
UNION ALL SELECT run_id, n || 'error', n || 'retry', 'error' FROM q WHERE event_type = 'error'
UNION ALL SELECT run_id, n || 'retry', n || 'ack', 'retry' FROM q WHERE event_type = 'error'
UNION ALL SELECT run_id, n || 'purchase', n || 'charge', 'purchase' FROM q WHERE event_type = 'purchase'
UNION ALL SELECT run_id, n || 'purchase', n || 'ship', 'purchase' FROM q WHERE event_type = 'purchase'
UNION ALL SELECT run_id, n || 'charge', n || 'ack', 'charge' FROM q WHERE event_type = 'purchase'
UNION ALL SELECT run_id, n || 'ship', n || 'ack', 'ship' FROM q WHERE event_type = 'purchase'
"""

# ---- F: a fork for each document of a source --------------------------------------------------
DOCUMENTS = Spec.chain("ROOT", [("ROOT", "source FORK sink"), ("FORK", "split {FORK DOC} gather"), ("FORK", "DOC"), ("DOC", "read tokenise write"), ("DOC", "read translate tokenise write")])


def _documents_nodes(spark: SparkSession, sf_dir: str, only: frozenset[str] | None = None) -> DataFrame:
    i, last = _rank(["source"], ["doc_id"])
    d = table(spark, sf_dir, "documents").select("source", "doc_id", "lang").select(F.col("source").alias("run_id"), "doc_id", "lang", i.alias("i"), last.alias("last"))
    ends = atoms(d.where("last"), DOCUMENTS, F.lit(1), F.col("run_id"), [], only=only)
    place = F.concat_ws(".", "run_id", F.col("doc_id").cast("string"))
    chain = [pos(1, 2), member(1, 1, F.col("i"))]
    forks = atoms(d.where("NOT last"), DOCUMENTS, F.lit(2), place, chain, only=only)
    own = [*chain, pos(F.when(F.col("last"), 3).otherwise(2), F.when(F.col("last"), 1).otherwise(3))]
    return ends.union(forks).union(atoms(d, DOCUMENTS, F.when(F.col("lang") == "en", 4).otherwise(5), place, own, only=only))


_DOCUMENTS_SQL = """
WITH d AS (
  SELECT source AS run_id, doc_id, lang, source || '.' || CAST(doc_id AS STRING) || '.' AS n,
         row_number() OVER (PARTITION BY source ORDER BY doc_id) AS i, lead(doc_id) OVER (PARTITION BY source ORDER BY doc_id) AS onward FROM {documents}),
h AS (SELECT *, n || CASE WHEN onward IS NULL THEN 'read' ELSE 'split' END AS head, n || CASE WHEN onward IS NULL THEN 'write' ELSE 'gather' END AS tail FROM d),
f AS (SELECT *, lead(head) OVER (PARTITION BY run_id ORDER BY i) AS next_head, lead(tail) OVER (PARTITION BY run_id ORDER BY i) AS next_tail FROM h)
SELECT run_id, run_id || '.source' AS src, head AS dst, 'source' AS tag FROM f WHERE i = 1
UNION ALL SELECT run_id, tail, run_id || '.sink', 'FORK' FROM f WHERE i = 1
UNION ALL SELECT run_id, head, next_head, 'split' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT run_id, head, n || 'read', 'split' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT run_id, next_tail, tail, 'FORK' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT run_id, n || 'write', tail, 'DOC' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT run_id, n || 'read', n || CASE WHEN lang = 'en' THEN 'tokenise' ELSE 'translate' END, 'read' FROM f
UNION ALL SELECT run_id, n || 'translate', n || 'tokenise', 'translate' FROM f WHERE NOT coalesce(lang = 'en', FALSE)
UNION ALL SELECT run_id, n || 'tokenise', n || 'write', 'tokenise' FROM f
"""

# ---- O: orders of a customer -------------------------------------------------------------------
_LINES = [("LINE", "pick pack ship done"), ("LINE", "pick pack hold ship done"), ("LINE", "pick pack ship inspect refund done")]
_ORDERS = [("CUST", "open ORDERS close"), ("ORDERS", "ORDER ORDERS"), ("ORDERS", "ORDER"), ("ORDER", "accept LINES settle")]
_ORDER_LINES = [("LINES", "LINE LINES"), ("LINES", "LINE"), *_LINES]
ORDERS = Spec.chain("CUST", [*_ORDERS, ("ORDER", "accept void settle"), *_ORDER_LINES])
FULL_ORDERS = Spec.chain("CUST", [*_ORDERS, *_ORDER_LINES])


def _orders_nodes(spark: SparkSession, sf_dir: str, full: bool, only: frozenset[str] | None = None) -> DataFrame:
    """All nodes, or those of some modules: lines are ranked only for modules that stand within a line."""
    spec, shift = (FULL_ORDERS, 4) if full else (ORDERS, 5)
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c"), F.col("o_orderkey").alias("o"), "o_orderdate")
    li = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("lo"), "l_linenumber", "l_partkey", "l_suppkey", "l_returnflag")
    has = li.where("lo IS NOT NULL").select(F.col("lo").alias("ho")).distinct()
    o = o.join(has, o["o"] == has["ho"], "inner" if full else "left").withColumn("void", F.col("ho").isNull()).drop("ho")
    b, last_b = _rank(["c"], ["o_orderdate", "o"])
    o = o.withColumn("b", b).withColumn("last_b", last_b).withColumn("run_id", F.concat(F.lit("c"), F.col("c").cast("string")))
    place = F.concat_ws(".", "run_id", F.concat(F.lit("o"), F.col("o").cast("string")))
    own = [pos(1, 2), member(1, 1, F.col("b")), pos(F.when(F.col("last_b"), 3).otherwise(2), 1)]

    def ends() -> DataFrame:
        return atoms(o.where("last_b"), spec, F.lit(1), F.col("run_id"), [], only=only)

    def orders() -> DataFrame:
        return atoms(o, spec, F.lit(4) if full else F.when(F.col("void"), 5).otherwise(4), place, own, only=only)

    def lines() -> DataFrame:
        c, last_c = _rank(["lo"], ["l_linenumber", "l_partkey", "l_suppkey"])
        ranked = li.withColumn("c_", c).withColumn("last_c", last_c).drop("l_linenumber", "l_partkey", "l_suppkey")
        x = o.join(ranked, o["o"] == ranked["lo"])
        kind = F.when(F.col("l_returnflag") == "A", 3).when(F.col("l_returnflag") == "N", 4).otherwise(5) + shift
        label = [*own, pos(4, 2), member(2, 1, F.col("c_")), pos(F.when(F.col("last_c"), shift + 2).otherwise(shift + 1), 1)]
        return atoms(x, spec, kind, F.concat(place, F.lit(".l"), F.col("c_").cast("string")), label, only=only)

    made = [(ends, {"open", "close"}), (orders, {"accept", "void", "settle"}), (lines, {m for _, body in _LINES for m in body.split()})]
    found = [make() for make, modules in made if only is None or modules & only] or [ends()]
    return functools.reduce(DataFrame.union, found)


def _orders_sql(full: bool) -> str:
    join = "JOIN" if full else "LEFT JOIN"
    return f"""
WITH l AS (
  SELECT l_orderkey AS lo, l_returnflag AS flag, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS c,
         count(*) OVER (PARTITION BY l_orderkey) AS n_lines FROM {{lineitem}}),
has AS (SELECT lo, n_lines FROM l WHERE c = 1),
o AS (
  SELECT 'c' || CAST(o_custkey AS STRING) AS run_id, o_orderkey AS o, n_lines,
         'c' || CAST(o_custkey AS STRING) || '.o' || CAST(o_orderkey AS STRING) || '.' AS n, o_orderdate
  FROM {{orders}} {join} has ON o_orderkey = lo),
s AS (
  SELECT *, lead(n) OVER (PARTITION BY run_id ORDER BY o_orderdate, o) AS next_n, lag(n) OVER (PARTITION BY run_id ORDER BY o_orderdate, o) AS before_n FROM o),
x AS (SELECT s.run_id, s.n, l.flag, l.c, l.n_lines, s.n || 'l' || CAST(l.c AS STRING) || '.' AS m, s.n || 'l' || CAST(l.c + 1 AS STRING) || '.' AS next_m FROM s JOIN l ON s.o = l.lo)
SELECT run_id, run_id || '.open' AS src, n || 'accept' AS dst, 'open' AS tag FROM s WHERE before_n IS NULL
UNION ALL SELECT run_id, n || 'settle', run_id || '.close', 'ORDERS' FROM s WHERE next_n IS NULL
UNION ALL SELECT run_id, n || 'settle', next_n || 'accept', 'ORDER' FROM s WHERE next_n IS NOT NULL
UNION ALL SELECT run_id, n || 'accept', n || 'void', 'accept' FROM s WHERE n_lines IS NULL
UNION ALL SELECT run_id, n || 'void', n || 'settle', 'void' FROM s WHERE n_lines IS NULL
UNION ALL SELECT run_id, n || 'accept', m || 'pick', 'accept' FROM x WHERE c = 1
UNION ALL SELECT run_id, m || 'done', n || 'settle', 'LINES' FROM x WHERE c = n_lines
UNION ALL SELECT run_id, m || 'done', next_m || 'pick', 'LINE' FROM x WHERE c < n_lines
UNION ALL SELECT run_id, m || 'pick', m || 'pack', 'pick' FROM x
UNION ALL SELECT run_id, m || 'pack', m || CASE WHEN flag = 'N' THEN 'hold' ELSE 'ship' END, 'pack' FROM x
UNION ALL SELECT run_id, m || 'hold', m || 'ship', 'hold' FROM x WHERE flag = 'N'
UNION ALL SELECT run_id, m || 'ship', m || CASE WHEN flag IN ('A', 'N') THEN 'done' ELSE 'inspect' END, 'ship' FROM x
UNION ALL SELECT run_id, m || 'inspect', m || 'refund', 'inspect' FROM x WHERE flag NOT IN ('A', 'N')
UNION ALL SELECT run_id, m || 'refund', m || 'done', 'refund' FROM x WHERE flag NOT IN ('A', 'N')
"""


# ---- C: turns of a conversation -----------------------------------------------------------------
TALKS = Spec.chain(
    "TALK",
    [
        ("TALK", "start ODD stop"), ("TALK", "start EVEN stop"), ("ODD", "TURN EVEN"), ("ODD", "TURN"), ("EVEN", "TURN note ODD"), ("EVEN", "TURN"),
        ("TURN", "hear log"), ("TURN", "think say log"), ("TURN", "configure log"),
    ],
)


def _talks_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    i, last = _rank(["conv_id"], ["turn"])
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    t = t.select(F.concat(F.lit("v"), F.col("conv_id").cast("string")).alias("run_id"), "role", i.alias("i"), last.alias("last"), (F.first("role").over(w) == "system").cast("int").alias("late"))
    begin = F.col("late") + 1  # which of the first two productions, and where the cycle is entered
    ends = atoms(t.where("last"), TALKS, begin, F.col("run_id"), [])
    odd = (F.col("i") + F.col("late")) % 2 == 1
    chain = [pos(begin, 2), member(1, begin, F.col("i"))]
    k = F.when(odd, F.when(F.col("last"), 4).otherwise(3)).otherwise(F.when(F.col("last"), 6).otherwise(5))
    place = F.concat(F.col("run_id"), F.lit(".t"), F.col("i").cast("string"))
    notes = atoms(t.where(~odd & ~F.col("last")), TALKS, F.lit(5), place, chain)
    kind = F.when(F.col("role") == "user", 7).when(F.col("role") == "assistant", 8).otherwise(9)
    return ends.union(notes).union(atoms(t, TALKS, kind, place, [*chain, pos(k, 1)]))


_TALKS_SQL = """
WITH t AS (
  SELECT 'v' || CAST(conv_id AS STRING) AS run_id, role, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS i,
         lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS next_role, first_value(role) OVER (PARTITION BY conv_id ORDER BY turn) AS opening FROM {conversations}),
h AS (
  SELECT *, run_id || '.t' || CAST(i AS STRING) || '.' AS n, run_id || '.t' || CAST(i + 1 AS STRING) || '.' AS next_n,
         CASE WHEN role = 'user' THEN 'hear' WHEN role = 'assistant' THEN 'think' ELSE 'configure' END AS head,
         CASE WHEN next_role = 'user' THEN 'hear' WHEN next_role = 'assistant' THEN 'think' ELSE 'configure' END AS next_head,
         (i + CASE WHEN opening = 'system' THEN 1 ELSE 0 END) % 2 AS odd FROM t)
SELECT run_id, run_id || '.start' AS src, n || head AS dst, 'start' AS tag FROM h WHERE i = 1
UNION ALL SELECT run_id, n || 'log', run_id || '.stop', CASE WHEN opening = 'system' THEN 'EVEN' ELSE 'ODD' END FROM h WHERE next_role IS NULL
UNION ALL SELECT run_id, n || 'log', next_n || next_head, 'TURN' FROM h WHERE next_role IS NOT NULL AND odd = 1
UNION ALL SELECT run_id, n || 'log', n || 'note', 'TURN' FROM h WHERE next_role IS NOT NULL AND odd = 0
UNION ALL SELECT run_id, n || 'note', next_n || next_head, 'note' FROM h WHERE next_role IS NOT NULL AND odd = 0
UNION ALL SELECT run_id, n || head, n || CASE WHEN head = 'think' THEN 'say' ELSE 'log' END, head FROM h
UNION ALL SELECT run_id, n || 'say', n || 'log', 'say' FROM h WHERE head = 'think'
"""

# ---- N: regions, nations and their suppliers ---------------------------------------------------
SUPPLY = Spec.chain(
    "WORLD",
    [
        ("WORLD", "hub {REGION REGION REGION REGION REGION} port"), ("REGION", "gate {NATION NATION NATION NATION NATION} dock"), ("NATION", "collect SUPS dispatch"), ("NATION", "collect idle dispatch"),
        ("SUPS", "split {SUPS SUP} merge"), ("SUPS", "SUP"), ("SUP", "load audit seal"), ("SUP", "load seal"),
    ],
)


def _supply_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    region = table(spark, sf_dir, "region").select("r_regionkey", F.row_number().over(Window.orderBy("r_regionkey")).alias("g"))
    m, _ = _rank(["n_regionkey"], ["n_nationkey"])
    nation = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey").withColumn("m", m.cast("int"))
    nation = nation.join(F.broadcast(region), nation["n_regionkey"] == region["r_regionkey"])
    r, last = _rank(["s_nationkey"], ["s_suppkey"])
    sup = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey", "s_acctbal").withColumn("r", r).withColumn("last", last)
    used = sup.where("r = 1").select(F.col("s_nationkey").alias("used"))
    nation = nation.join(used, nation["n_nationkey"] == used["used"], "left").withColumn("run_id", F.lit("world"))
    region = region.withColumn("run_id", F.lit("world"))
    ends = atoms(region.where("g = 1"), SUPPLY, F.lit(1), F.lit("w"), [])
    ends = ends.withColumn("node_id", F.col("module"))
    gates = atoms(region, SUPPLY, F.lit(2), F.concat(F.lit("r"), F.col("r_regionkey").cast("string")), [pos(1, 1 + F.col("g"))])
    at = [pos(1, 1 + F.col("g")), pos(2, 1 + F.col("m"))]
    nations = atoms(nation, SUPPLY, F.when(F.col("used").isNull(), 4).otherwise(3), F.concat(F.lit("n"), F.col("n_nationkey").cast("string")), at)
    x = sup.join(F.broadcast(nation), sup["s_nationkey"] == nation["n_nationkey"])
    place = F.concat(F.lit("s"), F.col("s_suppkey").cast("string"))
    chain = [*at, pos(3, 2), member(1, 1, F.col("r"))]
    forks = atoms(x.where("NOT last"), SUPPLY, F.lit(5), place, chain)
    own = [*chain, pos(F.when(F.col("last"), 6).otherwise(5), F.when(F.col("last"), 1).otherwise(3))]
    return ends.union(gates).union(nations).union(forks).union(atoms(x, SUPPLY, F.when(F.col("s_acctbal") < 0, 7).otherwise(8), place, own))


_SUPPLY_SQL = """
WITH s AS (
  SELECT s_nationkey AS k, 's' || CAST(s_suppkey AS STRING) || '.' AS n, s_acctbal AS bal, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_suppkey) AS r,
         lead(s_suppkey) OVER (PARTITION BY s_nationkey ORDER BY s_suppkey) AS onward FROM {supplier}),
h AS (SELECT *, n || CASE WHEN onward IS NULL THEN 'load' ELSE 'split' END AS head, n || CASE WHEN onward IS NULL THEN 'seal' ELSE 'merge' END AS tail FROM s),
f AS (SELECT *, lead(head) OVER (PARTITION BY k ORDER BY r) AS next_head, lead(tail) OVER (PARTITION BY k ORDER BY r) AS next_tail FROM h),
n AS (SELECT 'n' || CAST(n_nationkey AS STRING) || '.' AS c, 'r' || CAST(n_regionkey AS STRING) || '.' AS g, head, tail FROM {nation} LEFT JOIN f ON k = n_nationkey AND r = 1)
SELECT 'world' AS run_id, 'hub' AS src, 'r' || CAST(r_regionkey AS STRING) || '.gate' AS dst, 'hub' AS tag FROM {region}
UNION ALL SELECT 'world', 'r' || CAST(r_regionkey AS STRING) || '.dock', 'port', 'REGION' FROM {region}
UNION ALL SELECT 'world', g || 'gate', c || 'collect', 'gate' FROM n
UNION ALL SELECT 'world', c || 'dispatch', g || 'dock', 'NATION' FROM n
UNION ALL SELECT 'world', c || 'collect', coalesce(head, c || 'idle'), 'collect' FROM n
UNION ALL SELECT 'world', coalesce(tail, c || 'idle'), c || 'dispatch', CASE WHEN tail IS NULL THEN 'idle' ELSE 'SUPS' END FROM n
UNION ALL SELECT 'world', head, next_head, 'split' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT 'world', head, n || 'load', 'split' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT 'world', next_tail, tail, 'SUPS' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT 'world', n || 'seal', tail, 'SUP' FROM f WHERE onward IS NOT NULL
UNION ALL SELECT 'world', n || 'load', n || CASE WHEN bal < 0 THEN 'audit' ELSE 'seal' END, 'load' FROM f
UNION ALL SELECT 'world', n || 'audit', n || 'seal', 'audit' FROM f WHERE bal < 0
"""

# ---- P: pages of a host ------------------------------------------------------------------------
CRAWL = Spec.chain("CRAWL", [("CRAWL", "seed HOPS stop"), ("HOPS", "HOP HOPS"), ("HOPS", "HOP"), ("HOP", "fetch upgrade store"), ("HOP", "fetch store")])


def _crawl_nodes(spark: SparkSession, sf_dir: str, only: frozenset[str] | None = None) -> DataFrame:
    p = table(spark, sf_dir, "pages").select("page_id", "url").withColumn("host", F.regexp_extract("url", "^https?://([^/:?#]+)", 1))
    i, last = _rank(["host"], ["page_id"])
    p = p.select(F.concat(F.lit("h:"), F.col("host")).alias("run_id"), "page_id", "url", i.alias("i"), last.alias("last"))
    ends = atoms(p.where("last"), CRAWL, F.lit(1), F.col("run_id"), [], only=only)
    place = F.concat(F.col("run_id"), F.lit(".p"), F.col("page_id").cast("string"))
    own = [pos(1, 2), member(1, 1, F.col("i")), pos(F.when(F.col("last"), 3).otherwise(2), 1)]
    return ends.union(atoms(p, CRAWL, F.when(F.col("url").startswith("http:"), 4).otherwise(5), place, own, only=only))


_CRAWL_SQL = """
WITH h AS (SELECT 'h:' || regexp_extract(url, '^https?://([^/:?#]+)', 1) AS run_id, page_id, url LIKE 'http:%' AS plain FROM {pages}),
p AS (SELECT *, run_id || '.p' || CAST(page_id AS STRING) || '.' AS n FROM h),
q AS (SELECT *, lead(n) OVER (PARTITION BY run_id ORDER BY page_id) AS next_n, lag(n) OVER (PARTITION BY run_id ORDER BY page_id) AS before_n FROM p)
SELECT run_id, run_id || '.seed' AS src, n || 'fetch' AS dst, 'seed' AS tag FROM q WHERE before_n IS NULL
UNION ALL SELECT run_id, n || 'store', run_id || '.stop', 'HOPS' FROM q WHERE next_n IS NULL
UNION ALL SELECT run_id, n || 'store', next_n || 'fetch', 'HOP' FROM q WHERE next_n IS NOT NULL
UNION ALL SELECT run_id, n || 'fetch', n || CASE WHEN plain THEN 'upgrade' ELSE 'store' END, 'fetch' FROM q
UNION ALL SELECT run_id, n || 'upgrade', n || 'store', 'upgrade' FROM q WHERE plain
"""

# ---- X: the literal example run ----------------------------------------------------------------
EXAMPLE = Spec.build("S", [("S", ["c", "A", "B", "b"], [(1, 2), (1, 3), (2, 4), (3, 4)]), ("A", ["a", "A", "d"], [(1, 2), (2, 3)]), ("A", ["e", "e"], [(1, 2)]), ("B", ["b", "b"], [(1, 2)])])
#: The nodes of the example with their labels, (k, i) or (s, t, i), and its edges.
_EXAMPLE_NODES = {
    "c:1": [(1, 1)], "a:1": [(1, 2), (1, 1, 1), (2, 1)], "a:2": [(1, 2), (1, 1, 2), (2, 1)], "e:1": [(1, 2), (1, 1, 3), (3, 1)], "e:2": [(1, 2), (1, 1, 3), (3, 2)],
    "d:2": [(1, 2), (1, 1, 2), (2, 3)], "d:1": [(1, 2), (1, 1, 1), (2, 3)], "b:2": [(1, 3), (4, 1)], "b:3": [(1, 3), (4, 2)], "b:1": [(1, 4)],
}
_EXAMPLE_EDGES = "c:1 a:1 c, c:1 b:2 c, a:1 a:2 a, a:2 e:1 a, e:1 e:2 e, e:2 d:2 A, d:2 d:1 A, d:1 b:1 A, b:2 b:3 b, b:3 b:1 B"


def _example_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [("example", n, n[0], [(0, *e, 0) if len(e) == 2 else (1, *e) for e in label]) for n, label in _EXAMPLE_NODES.items()]
    return spark.createDataFrame(rows, "run_id string, node_id string, module string, label array<struct<kind:tinyint,a:int,b:int,idx:bigint>>")


_EXAMPLE_SQL = " UNION ALL ".join(f"SELECT 'example' AS run_id, '{u}' AS src, '{v}' AS dst, '{t}' AS tag" for u, v, t in (e.split() for e in _EXAMPLE_EDGES.split(", ")))



# ---- T: the example's grammar over the turns of a conversation -----------------------------------
def _nests_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each turn but the last is a level of nesting, and the last one its core."""
    t = table(spark, sf_dir, "conversations").select("conv_id", "turn").where("conv_id IS NOT NULL")
    i, last = _rank(["conv_id"], ["turn"])
    t = t.withColumn("i", i).withColumn("last", last).withColumn("run_id", F.concat(F.lit("v"), F.col("conv_id").cast("string")))
    chain = [pos(1, 2), member(1, 1, F.col("i"))]
    place = F.concat(F.lit(".t"), F.col("i").cast("string"), F.lit("."))

    def row(x: DataFrame, name: Column, module: str, *label: Column) -> DataFrame:
        return x.select("run_id", F.concat("run_id", name).alias("node_id"), F.lit(module).alias("module"), F.array(*label).alias("label"))

    one, inner, core = t.where("i = 1"), t.where("NOT last"), t.where("last")
    ends = [row(one, F.lit(".c"), "c", pos(1, 1)), row(one, F.lit(".1.b"), "b", pos(1, 3), pos(4, 1)), row(one, F.lit(".2.b"), "b", pos(1, 3), pos(4, 2)), row(one, F.lit(".b"), "b", pos(1, 4))]
    nested = [row(inner, F.concat(place, F.lit(m)), m, *chain, pos(2, j)) for m, j in (("a", 1), ("d", 3))]
    cores = [row(core, F.concat(place, F.lit(f"{j}.e")), "e", *chain, pos(3, j)) for j in (1, 2)]
    return functools.reduce(DataFrame.union, [*ends, *nested, *cores])


_NESTS_SQL = """
WITH t AS (
  SELECT 'v' || CAST(conv_id AS STRING) AS run_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS i, count(*) OVER (PARTITION BY conv_id) AS n_turns
  FROM {conversations} WHERE conv_id IS NOT NULL),
h AS (SELECT *, run_id || '.t' || CAST(i AS STRING) || CASE WHEN i = n_turns THEN '.1.e' ELSE '.a' END AS head, run_id || '.t' || CAST(i AS STRING) || CASE WHEN i = n_turns THEN '.2.e' ELSE '.d' END AS tail FROM t),
f AS (SELECT *, lead(head) OVER (PARTITION BY run_id ORDER BY i) AS next_head, lead(tail) OVER (PARTITION BY run_id ORDER BY i) AS next_tail FROM h)
SELECT run_id, run_id || '.c' AS src, head AS dst, 'c' AS tag FROM f WHERE i = 1
UNION ALL SELECT run_id, run_id || '.c', run_id || '.1.b', 'c' FROM f WHERE i = 1
UNION ALL SELECT run_id, run_id || '.1.b', run_id || '.2.b', 'b' FROM f WHERE i = 1
UNION ALL SELECT run_id, run_id || '.2.b', run_id || '.b', 'B' FROM f WHERE i = 1
UNION ALL SELECT run_id, tail, run_id || '.b', 'A' FROM f WHERE i = 1
UNION ALL SELECT run_id, head, next_head, 'a' FROM f WHERE i < n_turns
UNION ALL SELECT run_id, next_tail, tail, 'A' FROM f WHERE i < n_turns
UNION ALL SELECT run_id, head, tail, 'e' FROM f WHERE i = n_turns
"""

CARRIERS = {
    "events": Carrier("events", EVENTS, _EVENTS_SQL, _events_nodes, ("events",), _events_nodes),
    "documents": Carrier("documents", DOCUMENTS, _DOCUMENTS_SQL, _documents_nodes, ("documents",), _documents_nodes),
    "orders": Carrier("orders", ORDERS, _orders_sql(False), lambda s, d: _orders_nodes(s, d, False), ("orders", "lineitem"), lambda s, d, m: _orders_nodes(s, d, False, m)),
    "full_orders": Carrier("full_orders", FULL_ORDERS, _orders_sql(True), lambda s, d: _orders_nodes(s, d, True), ("orders", "lineitem"), lambda s, d, m: _orders_nodes(s, d, True, m)),
    "talks": Carrier("talks", TALKS, _TALKS_SQL, _talks_nodes, ("conversations",)),
    "supply": Carrier("supply", SUPPLY, _SUPPLY_SQL, _supply_nodes, ("region", "nation", "supplier")),
    "crawl": Carrier("crawl", CRAWL, _CRAWL_SQL, _crawl_nodes, ("pages",), _crawl_nodes),
    "example": Carrier("example", EXAMPLE, _EXAMPLE_SQL, _example_nodes, ()),
}
#: Not among the carriers, whose queries and verdicts are listed one by one.
NESTS = Carrier("nests", EXAMPLE, _NESTS_SQL, _nests_nodes, ("conversations",))
