"""Named workloads: each is a query over the tables and, where SQL can say it, its DuckDB text.

The SQL walks the run and the automaton together over edges that are derived without labels, so
it shares nothing with the methods it checks but the automaton.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath import experiments, measures
from wfpath.experiments import Simulated, SourceRuns
from wfpath.operators import allpairs, baseline, general, relational
from wfpath.plans import rpq
from wfpath.plans.safety import check_many, compile_rpq, is_safe
from wfpath.plans.spec import Spec
from wfpath.sources import runs, simulate
from wfpath.sources.runs import CARRIERS
from wfpath.streaming import labels as streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
FLAGSHIP = "fork_star_state_set"


_STORED: dict[tuple[str, str, str], runs.StoredRun] = {}


#: Simulated runs of the two workflows: one of each, and one of each in which only the fork's recursion goes on.
SIMULATED = {
    "deep": Simulated("deep", 300), "branchy": Simulated("branchy", 300),
    "deep_fork": Simulated("deep", 100, focus=experiments.focus_of("deep")), "branchy_fork": Simulated("branchy", 150, focus=experiments.focus_of("branchy")),
    "deep_small": Simulated("deep", 50), "branchy_small": Simulated("branchy", 50), "random": Simulated("random60", 200, seed=3),
}


#: Runs of the same workflows, and of the example's grammar, over given tables.
FROM_TABLES = {
    "deep_sources": SourceRuns("deep", 300), "branchy_sources": SourceRuns("branchy", 300),
    "deep_fork_sources": SourceRuns("deep", 100, experiments.focus_of("deep")), "branchy_fork_sources": SourceRuns("branchy", 150, experiments.focus_of("branchy")),
    "nests": runs.NESTS,
}


def carrier_of(name: str) -> runs.Carrier | Simulated | SourceRuns:
    return CARRIERS[name] if name in CARRIERS else FROM_TABLES[name] if name in FROM_TABLES else SIMULATED[name]


def run_of(carrier: str, spark: SparkSession, sf_dir: str) -> runs.StoredRun | runs.RunData:
    """A carrier's run, written once for an application: the first query on it pays for the writing.

    The short runs of sources aren't written: each query derives them from its own read of the table.
    """
    if isinstance(carrier_of(carrier), SourceRuns):
        return carrier_of(carrier).build(spark, sf_dir)
    key = (spark.sparkContext.applicationId, carrier, sf_dir)
    if key not in _STORED:
        _STORED[key] = carrier_of(carrier).stored(spark, sf_dir, f"{_folder(spark).rstrip('/')}/run-{carrier}-{uuid.uuid4().hex}")
    return _STORED[key]


def walk_sql(carrier: str, query: str, l1: str = "TRUE", l2: str = "TRUE", select: str = "SELECT DISTINCT run_id, src, node_id AS dst FROM hits") -> str:
    """The product walk of a query as recursive SQL; ``l1`` and ``l2`` are conditions on node_id and module."""
    c = carrier_of(carrier)
    dfa = rpq.compile_(rpq.rewrite(rpq.parse(query, c.spec.tags)), c.spec.tags)
    delta = ", ".join(f"({q}, '{t}', {r})" for q, t, r in dfa.table()) or "(-1, '', -1)"
    finals = ", ".join(map(str, sorted(dfa.finals))) or "-1"
    module = "CASE WHEN node_id LIKE '%:_' THEN node_id[1] ELSE regexp_extract(node_id, '[^.]+$') END"
    return f"""
WITH RECURSIVE edges AS (SELECT * FROM ({c.duckdb()}) AS e0),
delta(q, tag, q2) AS (VALUES {delta}),
nodes AS (SELECT run_id, node_id, {module} AS module FROM (SELECT run_id, src AS node_id FROM edges UNION SELECT run_id, dst FROM edges) AS n0),
l1 AS (SELECT run_id, node_id FROM nodes WHERE {l1}),
l2 AS (SELECT run_id, node_id FROM nodes WHERE {l2}),
g AS (SELECT run_id, src, q, dst, q2 FROM edges JOIN delta USING (tag)),
walk(run_id, src, node_id, q) AS (
  SELECT run_id, node_id, node_id, 0 FROM l1
  UNION SELECT w.run_id, w.src, g.dst, g.q2 FROM walk AS w JOIN g ON g.run_id = w.run_id AND g.src = w.node_id AND g.q = w.q),
hits AS (SELECT DISTINCT w.run_id, w.src, w.node_id FROM walk AS w JOIN l2 ON l2.run_id = w.run_id AND l2.node_id = w.node_id WHERE w.q IN ({finals}))
{select}
"""


def _within(modules: str | None) -> str:
    return "TRUE" if modules is None else "module IN (" + ", ".join(f"'{m}'" for m in modules.split()) + ")"


def _list(data: runs.StoredRun, modules: str | None) -> DataFrame | None:
    return None if modules is None else data.part(modules.split()).select("run_id", "node_id", "label")


def pairs(key: str, carrier: str, query: str, methods: str, l1: str | None = None, l2: str | None = None) -> None:
    """All-pairs workloads, one for each method; the key of the first is ``key`` if only one is named."""
    for m in methods.split():

        def run(spark: SparkSession, sf_dir: str, m=m) -> DataFrame:
            data = run_of(carrier, spark, sf_dir)
            return general.evaluate(data, query, _list(data, l1), _list(data, l2), m)

        name = key if len(methods.split()) == 1 else f"{key}_{m}"
        QUERIES[name], ORACLES[name] = run, walk_sql(carrier, query, _within(l1), _within(l2))


def outputs(key: str, carrier: str, query: str, l1: str | None = None, l2: str | None = None) -> None:
    """The grouped method's other outputs: counts by run, runs with a match, sources, targets."""
    selects = {
        "count": "SELECT run_id, count(*) AS n FROM hits GROUP BY run_id",
        "exists": "SELECT DISTINCT run_id FROM hits",
        "sources": "SELECT DISTINCT run_id, src AS node_id FROM hits",
        "targets": "SELECT DISTINCT run_id, node_id FROM hits",
    }
    for out, select in selects.items():

        def run(spark: SparkSession, sf_dir: str, out=out) -> DataFrame:
            data = run_of(carrier, spark, sf_dir)
            u, v = _list(data, l1), _list(data, l2)
            return allpairs.state_set(general.labelled(data, u, v), compile_rpq(data.spec, query), u, v, out)

        QUERIES[f"{key}_{out}"], ORACLES[f"{key}_{out}"] = run, walk_sql(carrier, query, _within(l1), _within(l2), select)


def probes(key: str, carrier: str, query: str, l1: str, l2: str, method: str = "labels") -> None:
    """Pairwise workloads: every pair of the named modules' nodes of a run, decided one by one."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        data = run_of(carrier, spark, sf_dir)
        u = _list(data, l1).select("run_id", F.col("node_id").alias("src"))
        v = _list(data, l2).select("run_id", F.col("node_id").alias("dst"))
        if method == "arrays":
            from wfpath.operators import pairwise

            return pairwise.holds(u.join(v, "run_id"), data.nodes, compile_rpq(data.spec, query), "arrays")
        return general.holds(data, query, u.join(v, "run_id"), method)

    select = "SELECT l1.run_id, l1.node_id AS src, l2.node_id AS dst, hits.src IS NOT NULL AS holds FROM l1 JOIN l2 USING (run_id) LEFT JOIN hits ON hits.run_id = l1.run_id AND hits.src = l1.node_id AND hits.node_id = l2.node_id"
    QUERIES[key], ORACLES[key] = run, walk_sql(carrier, query, _within(l1), _within(l2), select)


def values(key: str, columns: str, rows: list[tuple], make: Callable[[SparkSession, str], DataFrame]) -> None:
    """A workload whose answer is a fixed table."""
    text = ", ".join("(" + ", ".join(f"'{x}'" if isinstance(x, str) else str(x).upper() if isinstance(x, bool) else str(x) for x in r) + ")" for r in rows)
    QUERIES[key], ORACLES[key] = make, f"SELECT * FROM (VALUES {text}) AS t({columns})"


# ---- the worked example ------------------------------------------------------------------------
SAFE_METHODS = "nested filtered state_set walk joins"
pairs("example_plus", "example", "A+", SAFE_METHODS)
pairs("example_plus_joins", "nests", "A+", "joins")
pairs("example_single", "example", "A", "state_set")
pairs("example_pass_e", "example", "_*.e._*", "nested filtered state_set index index_nested rare_tag")
pairs("example_star", "example", "a*", "state_set joins_linear joins joins_double decompose")
pairs("example_unsafe_tag", "example", "e", "joins decompose")
pairs("example_unsafe_pass", "example", "_*.a._*", "joins rare_tag decompose decompose_runs decompose_bottom_up")
pairs("example_reach", "example", "_*", "nested filtered state_set")
#: Verdicts of the example's queries.
_EXAMPLE_SAFE = [("A+", True), ("A", True), ("_*.e._*", True), ("e", False), ("_*.a._*", False), ("_*", True), ("a*", True)]
values("example_safety", "query, safe", _EXAMPLE_SAFE, lambda s, d: s.createDataFrame([(q, is_safe(runs.EXAMPLE, q)) for q, _ in _EXAMPLE_SAFE], "query string, safe boolean"))

# ---- safety of the carriers' queries -----------------------------------------------------------
#: Tags whose passing query is safe, for each carrier; those of all other tags are unsafe.
_SAFE_TAGS = {
    "events": "begin arrive STEPS SESS", "orders": "open accept ORDERS", "full_orders": "open accept ORDERS LINES pick pack ship", "documents": "source read tokenise",
    "talks": "start", "supply": "hub gate collect NATION REGION", "crawl": "seed fetch HOPS",
}
#: Tags whose star is unsafe.
_UNSAFE_STARS = {"events": "click view", "orders": "", "full_orders": "", "documents": "", "talks": "configure hear", "supply": "load", "crawl": "fetch"}
_ALL_TAGS = {
    "events": "begin arrive STEPS SESS VISIT STEP click view signup verify purchase charge ship error retry", "orders": "open accept ORDERS LINE LINES ORDER hold inspect pack pick refund ship void",
    "full_orders": "open accept ORDERS LINES pick pack ship LINE ORDER hold inspect refund", "documents": "source read tokenise DOC FORK split translate",
    "talks": "start EVEN ODD TURN configure hear note say think", "supply": "hub gate collect NATION REGION SUP SUPS audit idle load split", "crawl": "seed fetch HOPS HOP upgrade",
}
_CATALOGUE = [(c, f"_*.{t}._*", t in _SAFE_TAGS[c].split()) for c in _SAFE_TAGS for t in _ALL_TAGS[c].split()]
_CATALOGUE += [(c, f"{t}*", t not in _UNSAFE_STARS[c].split()) for c in _SAFE_TAGS for t in _ALL_TAGS[c].split()]
values("safety_catalogue", "carrier, query, safe", _CATALOGUE, lambda s, d: s.createDataFrame([(c, f"{q}", is_safe(CARRIERS[c].spec, q)) for c in _SAFE_TAGS for t in CARRIERS[c].spec.tags for q in (f"_*.{t}._*", f"{t}*")], "carrier string, query string, safe boolean"))
#: Longer passing queries and their verdicts.
_LONGER = [
    ("events", "begin arrive STEPS", True), ("events", "arrive STEPS", True), ("events", "begin SESS", True), ("events", "arrive arrive", False), ("events", "STEPS arrive", False),
    ("orders", "open accept ORDERS", True), ("orders", "accept pick", False), ("full_orders", "accept pick ship", True), ("full_orders", "open accept pick pack ship LINES ORDERS", True),
    ("full_orders", "ship pick", False), ("documents", "source read tokenise", True), ("documents", "split read", False), ("talks", "start TURN", False), ("talks", "note note", False),
    ("supply", "hub gate NATION REGION", True), ("supply", "gate load", False), ("crawl", "seed fetch HOPS", True),
]
values("safety_longer", "carrier, tags, safe", _LONGER, lambda s, d: s.createDataFrame([(c, t, is_safe(CARRIERS[c].spec, rpq.ifq(t.split()))) for c, t, _ in _LONGER], "carrier string, tags string, safe boolean"))
values("safety_narrowing", "carrier, safe", [("orders", False), ("full_orders", True)], lambda s, d: s.createDataFrame([(c, is_safe(CARRIERS[c].spec, "_*.pick._*")) for c in ("orders", "full_orders")], "carrier string, safe boolean"))
_DEEP_ORDER = "open accept pick pack ship LINES ORDERS".split()
values("safety_by_k", "k, safe", [(k, True) for k in range(8)], lambda s, d: s.createDataFrame([(k, is_safe(runs.FULL_ORDERS, rpq.ifq(_DEEP_ORDER[:k]))) for k in range(8)], "k int, safe boolean"))
#: Size, modules, composite modules, productions, recursive productions.
_STATISTICS = [("deep", 166, 112, 16, 23, 7), ("branchy", 105, 77, 11, 15, 5)]


def _statistics(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wfpath.plans.spec import branchy_like, deep_like

    return spark.createDataFrame([(n, *s.statistics.values()) for n, s in (("deep", deep_like()), ("branchy", branchy_like()))], "name string, size int, modules int, composite int, productions int, recursive int")


values("spec_statistics", "name, size, modules, composite, productions, recursive", _STATISTICS, _statistics)

# ---- pairwise ----------------------------------------------------------------------------------
probes("pairwise_ifq_events", "events", "_*.begin._*.arrive._*.STEPS._*", "begin arrive", "leave end")
probes("pairwise_ifq_orders", "full_orders", "_*.accept._*.pick._*.ship._*", "open accept", "settle close")
probes("pairwise_ifq_supply", "supply", "_*.hub._*.gate._*.REGION._*", "hub gate", "port dock")
probes("pairwise_ifq_supply_arrays", "supply", "_*.hub._*.gate._*.REGION._*", "hub gate", "port dock", "arrays")
probes("pairwise_ifq_crawl_rare_tag", "crawl", "_*.seed._*", "seed", "store stop", "rare_tag")
probes("pairwise_ifq_crawl_index", "crawl", "_*.seed._*.fetch._*", "seed", "store stop", "index")
probes("pairwise_unsafe_crawl", "crawl", "_*.upgrade._*", "seed fetch", "stop", "auto")
for _k in range(5):
    probes(f"pairwise_ifq_k{_k}", "full_orders", str(rpq.ifq(_DEEP_ORDER[:_k])), "open", "settle close")

# ---- all pairs, passing queries ----------------------------------------------------------------
pairs("ifq_sel_supply", "supply", "_*.hub._*.REGION._*", "nested filtered state_set index")
pairs("ifq_sel_orders", "full_orders", "_*.open._*.ORDERS._*", "filtered state_set", "open accept", "settle close")
pairs("ifq_sel_documents", "documents", "_*.source._*.read._*", "nested filtered state_set index", "source", "sink")
pairs("ifq_sel_events", "events", "_*.begin._*.SESS._*", "nested state_set", "begin", "leave end")
pairs("ifq_unsel_orders", "full_orders", "_*.pick._*.pack._*.ship._*", "filtered state_set", "accept", "settle")
pairs("ifq_unsel_documents", "documents", "_*.read._*.tokenise._*", "nested state_set index", "split read", "gather sink")
pairs("ifq_unsel_events", "events", "_*.arrive._*.STEPS._*", "nested filtered state_set", "arrive", "leave")
outputs("ifq_orders", "full_orders", "_*.accept._*.pick._*", "accept", "settle")
outputs("ifq_documents", "documents", "_*.read._*", "split read", "gather sink")

# ---- all pairs, stars --------------------------------------------------------------------------
pairs("fork_star", "documents", "split*", "nested filtered state_set joins joins_linear joins_double")
pairs("supply_star", "supply", "split*", "nested filtered state_set joins")
pairs("verify_star", "events", "verify*", "state_set joins", "verify signup", "ack verify signup")

# ---- general queries ---------------------------------------------------------------------------
pairs("general_mix_1", "events", "_*.error._*", "decompose rare_tag", "begin", "end")
pairs("general_mix_2", "events", "click.(STEP.click)*", "joins decompose_runs", "click", "ack")
pairs("general_mix_3", "documents", "split*.(_*.translate._*)", "decompose decompose_runs decompose_bottom_up", "split", "sink")
pairs("general_mix_4", "full_orders", "_*.(hold|inspect)._*", "decompose", "open", "close")
pairs("general_mix_5", "orders", "accept.pick.pack.ship.inspect.refund", "joins decompose_runs")
pairs("general_mix_6", "talks", "_*.think._*", "walk joins decompose decompose_runs", "start hear", "log stop")
pairs("general_mix_7", "supply", "_*.audit._*", "joins rare_tag decompose decompose_runs decompose_bottom_up auto")
pairs("general_mix_8", "crawl", "_*.upgrade._*", "rare_tag decompose decompose_runs auto", "seed fetch", "store stop")

# ---- other uses --------------------------------------------------------------------------------
pairs("intro_events", "events", "arrive.((click|view).STEP)*.(click|view).STEPS._*.SESS", "decompose_runs", "arrive", "end")
pairs("intro_orders", "full_orders", "accept.(pick|pack|hold|ship|LINE)+.LINES._*.ORDERS", "decompose_runs", "accept", "close")
pairs("reach_orders", "full_orders", "_*", "state_set", "accept", "refund")
pairs("reach_supply", "supply", "_*", "nested filtered state_set", "load", "port")
pairs("choice_orders", "full_orders", "pick.pack.ship.inspect.refund", "joins", "pick", "done")
pairs("conv_cycle_start", "talks", "_*.start._*", "nested filtered state_set")
pairs("conv_cycle_notes", "talks", "_*.note._*.note._*", "joins decompose_runs", "start hear", "stop log")
pairs("conv_cycle_say", "talks", "_*.think.say.TURN._*", "decompose_runs", "start hear think", "stop log")
pairs("conv_cycle_turns", "talks", "((hear|configure).TURN.note?)+", "joins joins_double decompose")
pairs("crawl_reach", "crawl", "_*", "state_set", "seed", "store stop")


def lineage(key: str, chosen_sql: str, make: Callable[[SparkSession, str], DataFrame]) -> None:
    """Read nodes of chosen documents (run_id, doc_id) to the outputs of their source."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        data = run_of("documents", spark, sf_dir)
        l1 = make(spark, sf_dir).select(F.col("source").alias("run_id"), F.concat_ws(".", "source", F.col("doc_id").cast("string"), F.lit("read")).alias("node_id"))
        return allpairs.state_set(data.nodes, compile_rpq(data.spec, "_*.tokenise._*"), l1, _list(data, "gather sink"))

    QUERIES[key] = run
    ORACLES[key] = walk_sql("documents", "_*.tokenise._*", f"node_id IN (SELECT source || '.' || CAST(doc_id AS VARCHAR) || '.read' FROM ({chosen_sql}))", _within("gather sink"))


def _window_key(n: int) -> Callable:
    return lambda i: F.xxhash64(F.array_join(F.slice("words", i, n), " "))


def _contaminated(spark: SparkSession, sf_dir: str, most: int = 8) -> DataFrame:
    """Documents that hold an item of the benchmark.

    Between its first and last space an item's words are whole words of any text that holds it, so
    up to ``most`` of them are its key and all windows of so many words a text's; what meets is verified.
    """
    words = lambda c: F.split(c, " ")
    items = runs.table(spark, sf_dir, "benchmark").select(F.col("text").alias("item")).where("item IS NOT NULL").distinct()
    items = items.withColumn("width", F.least(F.lit(most), F.size(words("item")) - 2))
    docs = runs.table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    found = None
    for (n,) in items.select("width").distinct().orderBy("width").collect():  # at most ``most`` + 2 widths
        some = items.where(F.col("width") == n)
        if n < 1:
            # one or two words have no inner one: such items, if any, are looked for one by one, and have to be few
            if some.limit(1001).count() > 1000:
                raise ValueError("too many items of one or two words")
            met = docs.join(F.broadcast(some.select("item")), F.contains("text", "item"), "left_semi").select("source", "doc_id")
        else:
            keyed = some.select("item", F.xxhash64(F.array_join(F.slice(words("item"), 2, n), " ")).alias("key"))
            at = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size("words") - n + 1))
            windows = docs.withColumn("words", words("text")).select("doc_id", "source", F.explode(F.transform(at, _window_key(n))).alias("key"))
            near = windows.join(keyed, "key").select("doc_id", "source", "item").distinct()
            met = docs.join(near, ["doc_id", "source"]).where(F.contains("text", "item")).select("source", "doc_id")
        found = met if found is None else found.union(met)
    return docs.select("source", "doc_id").limit(0) if found is None else found.distinct()


lineage("contamination_lineage", "SELECT source, doc_id FROM documents WHERE EXISTS (SELECT 1 FROM benchmark b WHERE contains(documents.text, b.text))", _contaminated)
lineage("quality_lineage", "SELECT source, doc_id FROM documents SEMI JOIN (SELECT * FROM labels WHERE quality = 1) USING (doc_id)", lambda s, d: runs.table(s, d, "documents").join(runs.table(s, d, "labels").where("quality = 1"), "doc_id", "left_semi"))
lineage("cluster_lineage", "SELECT source, doc_id FROM documents SEMI JOIN (SELECT vec_id AS doc_id FROM embeddings WHERE label = 3) USING (doc_id)", lambda s, d: runs.table(s, d, "documents").join(runs.table(s, d, "embeddings").where("label = 3").select(F.col("vec_id").alias("doc_id")), "doc_id", "left_semi"))

# ---- tables around the methods -----------------------------------------------------------------
for _c in ("events", "documents", "orders", "full_orders", "talks", "supply", "crawl"):
    QUERIES[f"run_edges_{_c}"], ORACLES[f"run_edges_{_c}"] = (lambda s, d, c=_c: CARRIERS[c].edges(s, d)), CARRIERS[_c].duckdb()
    QUERIES[f"run_nodes_{_c}"] = lambda s, d, c=_c: CARRIERS[c].nodes(s, d).select("run_id", "node_id")
    ORACLES[f"run_nodes_{_c}"] = f"WITH e AS (SELECT * FROM ({CARRIERS[_c].duckdb()}) AS e0) SELECT run_id, src AS node_id FROM e UNION SELECT run_id, dst FROM e"
    QUERIES[f"tag_counts_{_c}"] = lambda s, d, c=_c: CARRIERS[c].edges(s, d).groupBy("tag").agg(F.count(F.lit(1)).alias("n"))
    ORACLES[f"tag_counts_{_c}"] = f"SELECT tag, count(*) AS n FROM ({CARRIERS[_c].duckdb()}) AS e GROUP BY tag"
    QUERIES[f"run_sizes_{_c}"] = lambda s, d, c=_c: measures.described(CARRIERS[c].build(s, d))
    ORACLES[f"run_sizes_{_c}"] = f"""WITH e AS (SELECT * FROM ({CARRIERS[_c].duckdb()}) AS e0), n AS (SELECT run_id, count(*) AS n_nodes FROM (SELECT run_id, src FROM e UNION SELECT run_id, dst FROM e) AS x GROUP BY run_id)
SELECT e.run_id, n_nodes, count(*) AS n_edges, count(DISTINCT tag) AS n_tags FROM e JOIN n ON n.run_id = e.run_id GROUP BY e.run_id, n_nodes"""


def _product(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = CARRIERS["example"]
    return baseline.product_graph(c.edges(spark, sf_dir), rpq.compile_(rpq.parse("_*.e._*"), c.spec.tags))


QUERIES["product_graph_example"] = _product
_dfa = rpq.compile_(rpq.parse("_*.e._*"), runs.EXAMPLE.tags)
ORACLES["product_graph_example"] = f"SELECT run_id, src, q, dst, q2, e.tag FROM ({CARRIERS['example'].duckdb()}) AS e JOIN (VALUES {', '.join(str(x) for x in _dfa.table())}) AS d(q, tag, q2) ON d.tag = e.tag"
QUERIES["measure_reachable_supply"] = lambda s, d: measures.reachable_pairs(run_of("supply", s, d)).select("run_id", "reachable", "tested")
ORACLES["measure_reachable_supply"] = walk_sql("supply", "_*", select="SELECT run_id, count(*) AS reachable, (SELECT count(*) * count(*) FROM nodes) AS tested FROM hits GROUP BY run_id")
QUERIES["measure_selectivity_documents"] = lambda s, d: measures.selectivity(general.evaluate(run_of("documents", s, d), "split*", method="state_set"))
ORACLES["measure_selectivity_documents"] = walk_sql("documents", "split*", select="SELECT run_id, count(*) AS pairs FROM hits GROUP BY run_id")
QUERIES["measure_diff_supply"] = lambda s, d: measures.diff(general.evaluate(run_of("supply", s, d), "split*", method="state_set"), general.evaluate(run_of("supply", s, d), "split*", method="walk"))
ORACLES["measure_diff_supply"] = "SELECT '' AS run_id, '' AS src, '' AS dst, '' AS side WHERE FALSE"
QUERIES["measure_label_lengths"] = lambda s, d: measures.label_lengths(CARRIERS["orders"].build(s, d))
QUERIES["levels_documents"] = lambda s, d: _levels(s, d)
QUERIES["stream_labels"] = lambda s, d: streams.with_keys(streams.stored(streams.labelled(streams.stream_of(s, d)), _folder(s)))
QUERIES["stream_hourly"] = lambda s, d: streams.replaced(streams.hourly(streams.stream_of(s, d)), _folder(s))
ORACLES["stream_hourly"] = "SELECT date_trunc('hour', ts) AT TIME ZONE 'UTC' AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"
QUERIES["event_sessions"] = lambda s, d: runs.events_ranked(runs.table(s, d, "events")).groupBy("run_id", "a").agg(F.count(F.lit(1)).alias("n"), F.min("us").alias("first_us"), F.max("us").alias("last_us"))
ORACLES["event_sessions"] = """
WITH e AS (SELECT 'u' || CAST(user_id AS VARCHAR) AS run_id, event_id, epoch_us(ts) AS us FROM events),
g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY run_id ORDER BY us, event_id) <= 43200000000 THEN 0 ELSE 1 END AS fresh FROM e),
s AS (SELECT *, CAST(sum(fresh) OVER (PARTITION BY run_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS a FROM g)
SELECT run_id, a, count(*) AS n, min(us) AS first_us, max(us) AS last_us FROM s GROUP BY run_id, a"""
QUERIES["supply_rollup"] = lambda s, d: _rollup(s, d)
ORACLES["supply_rollup"] = "SELECT r_name, n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)"


_folder = baseline.shared_folder


def _levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    from wfpath.functions.labels import levels

    c = CARRIERS["documents"]
    x = levels(c.nodes(spark, sf_dir), c.spec)
    return x.select("run_id", "node_id", "depth", F.lower(F.hex("prefix")).alias("prefix"), "colour")


def _augmented(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the example's query can do inside each module, and how often the nests' runs execute it.

    A composite module is executed once for each first place of one of its productions' bodies.
    """
    from wfpath.plans.safety import augment

    head = {p.number: p.lhs for p in runs.EXAMPLE.productions}
    own = F.element_at("label", -1)
    expanded = F.when(own["b"] == 1, F.element_at(F.create_map(*[F.lit(x) for pair in head.items() for x in pair]), own["a"]))
    ran = run_of("nests", spark, sf_dir).nodes.select(F.explode(F.array("module", expanded)).alias("module")).where("module IS NOT NULL").groupBy("module").agg(F.count(F.lit(1)).alias("executions"))
    return augment(spark, compile_rpq(runs.EXAMPLE, "_*.e._*"))["gr_inner"].join(ran, "module")


def _rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: runs.table(spark, sf_dir, n)
    x = t("supplier").join(F.broadcast(t("nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return x.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("suppliers"))


# ---- the two workflows of the experiments --------------------------------------------------------
for _w in ("deep", "branchy"):
    for _i, _q in enumerate(experiments.passing(_w, 3, 8)):
        pairs(f"{_w}_ifq_{_i}", _w, _q, "nested filtered state_set index" if _i in (0, 7) else "state_set")
    pairs(f"{_w}_star", f"{_w}_fork", f"{experiments.star_tag(_w)}*", "nested filtered state_set joins joins_double")
    for _i, _q in enumerate(experiments.unsafe(_w, 3, n_ops=2)):
        pairs(f"{_w}_unsafe_{_i}", f"{_w}_small", str(_q), "joins_double decompose_runs")
    pairs(f"{_w}_operands_2_safe", f"{_w}_small", str(experiments.with_safe_operands(_w, 4, 2)), "decompose_runs")
    QUERIES[f"run_edges_{_w}"], ORACLES[f"run_edges_{_w}"] = (lambda s, d, w=_w: SIMULATED[w].build(s).edges), SIMULATED[_w].duckdb()
    QUERIES[f"run_edges_{_w}_fork"], ORACLES[f"run_edges_{_w}_fork"] = (lambda s, d, w=_w: SIMULATED[f"{w}_fork"].build(s).edges), SIMULATED[f"{_w}_fork"].duckdb()
# one run for each source of documents
for _w in ("deep", "branchy"):
    for _i in (0, 7):
        pairs(f"{_w}_ifq_{_i}_nested", f"{_w}_sources", experiments.passing(_w, 3, 8)[_i], "nested")
    pairs(f"{_w}_star_nested", f"{_w}_fork_sources", f"{experiments.star_tag(_w)}*", "nested")
pairs("branchy_star_joins", "branchy_fork_sources", f"{experiments.star_tag('branchy')}*", "joins")
pairs("branchy_star_joins_double", "branchy_fork_sources", f"{experiments.star_tag('branchy')}*", "joins_double")
pairs("random_reach", "random", "_*", "filtered state_set")
_DEEP_ENDS = sorted({m for _, m, _ in experiments.derive(SIMULATED["deep"].spec, 300, 0)[0]})
_L1, _L2 = " ".join(_DEEP_ENDS[:12]), " ".join(_DEEP_ENDS[-12:])
for _m in ("labels", "rare_tag", "index"):
    probes(f"deep_pairwise_{_m}", "deep", experiments.passing("deep", 3, 8)[0], _L1, _L2, _m)
for _k in (0, 1, 5, 7, 10):
    probes(f"deep_pairwise_k{_k}", "deep", experiments.passing("deep", _k, 2)[-1], _L1, _L2)
QUERIES["matched_by_workflow"] = lambda s, d: experiments.matched_by_workflow(s, lambda one: run_of(one.name, s, d))
ORACLES["matched_by_workflow"] = " UNION ALL ".join(
    f"SELECT '{w}' AS workflow, {i} AS i, (SELECT count(*) FROM ({walk_sql(w, q)}) AS p) AS pairs" for w in ("deep", "branchy") for i, q in enumerate(experiments.passing(w, 3, 4))
)

# ---- relational operators around the methods -----------------------------------------------------
QUERIES["top_sources"] = lambda s, d: relational.top_sources(general.evaluate(run_of("supply", s, d), "split*", method="state_set"), 10)
ORACLES["top_sources"] = walk_sql("supply", "split*", select="SELECT run_id, src, count(*) AS n FROM hits GROUP BY run_id, src ORDER BY n DESC, run_id, src LIMIT 10")
QUERIES["top_sources_by_run"] = lambda s, d: relational.top_sources(general.evaluate(run_of("documents", s, d), "split*", method="state_set"), 3, by_run=True)
ORACLES["top_sources_by_run"] = walk_sql("documents", "split*", select="SELECT run_id, src, n FROM (SELECT run_id, src, count(*) AS n, row_number() OVER (PARTITION BY run_id ORDER BY count(*) DESC, src) AS r FROM hits GROUP BY run_id, src) AS c WHERE r <= 3")
QUERIES["module_cube"] = lambda s, d: relational.module_cube(general.evaluate(run_of("supply", s, d), "_*.gate._*", method="state_set"), run_of("supply", s, d).nodes)
ORACLES["module_cube"] = walk_sql("supply", "_*.gate._*", select="SELECT a.module AS src_module, b.module AS dst_module, count(*) AS n FROM hits JOIN nodes a ON a.node_id = hits.src JOIN nodes b ON b.node_id = hits.node_id GROUP BY CUBE (a.module, b.module)")


def _sessions_at(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each purchase with the start of the last session of its user that had begun."""
    e = runs.table(spark, sf_dir, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    starts = runs.events_ranked(runs.table(spark, sf_dir, "events")).where("b = 1").select(F.substring("run_id", 2, 20).cast("bigint").alias("user_id"), "us", F.col("us").alias("session_us"))
    return relational.as_of(e.where("event_type = 'purchase'").select("user_id", "us", "event_id"), starts, ["user_id"], "us", "session_us")


QUERIES["as_of_sessions"] = _sessions_at
_FRESH = """
WITH e AS (SELECT user_id, event_id, event_type, epoch_us(ts) AS us FROM events),
g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY user_id ORDER BY us, event_id) <= 43200000000 THEN 0 ELSE 1 END AS fresh FROM e)"""
ORACLES["as_of_sessions"] = f"{_FRESH} SELECT p.user_id, p.us, p.event_id, (SELECT max(us) FROM g WHERE fresh = 1 AND g.user_id = p.user_id AND g.us <= p.us) AS session_us FROM e AS p WHERE p.event_type = 'purchase'"


def _clicks(spark: SparkSession, sf_dir: str, kind: str, name: str, stream: bool = False) -> DataFrame:
    e = (streams.stream_of(spark, sf_dir) if stream else runs.table(spark, sf_dir, "events")).where(F.col("event_type") == kind)
    return e.select(F.col("user_id").cast("bigint").alias("user_id"), F.col("event_id").cast("bigint").alias(name), F.col("ts").cast("timestamp").alias(f"{name}_ts"))


def _range_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    micros = lambda x, name: x.select("user_id", name, F.unix_micros(f"{name}_ts").alias(f"{name}_us"))
    a, b = micros(_clicks(spark, sf_dir, "click", "click"), "click"), micros(_clicks(spark, sf_dir, "purchase", "purchase"), "purchase")
    return relational.within_range(a, b, ["user_id"], "click_us", "purchase_us", 21_600_000_000)


QUERIES["range_pairs"] = _range_pairs
ORACLES["range_pairs"] = "SELECT a.user_id, a.event_id AS click, epoch_us(a.ts) AS click_us, b.event_id AS purchase, epoch_us(b.ts) AS purchase_us FROM events a JOIN events b ON a.user_id = b.user_id AND epoch_us(b.ts) - epoch_us(a.ts) BETWEEN 0 AND 21599999999 WHERE a.event_type = 'click' AND b.event_type = 'purchase'"
QUERIES["stream_interval_pairs"] = lambda s, d: streams.stored(streams.followed(_clicks(s, d, "click", "click", True), _clicks(s, d, "purchase", "purchase", True), ["user_id"], "click_ts", "purchase_ts", "6 HOURS", "60 days"), _folder(s)).select("user_id", "click", "purchase")
ORACLES["stream_interval_pairs"] = "SELECT a.user_id, a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOURS WHERE a.event_type = 'click' AND b.event_type = 'purchase'"


def _probe_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A probe for each arriving event: does its user's run pass a session's steps on its way to the end?"""
    data = run_of("events", spark, sf_dir)
    run = F.concat(F.lit("u"), F.col("user_id").cast("string"))
    probes_ = streams.stream_of(spark, sf_dir).select("event_id", run.alias("run_id"), F.concat(run, F.lit(".begin")).alias("src"), F.concat(run, F.when(F.col("event_type") == "error", ".begin").otherwise(".end")).alias("dst"))
    return streams.stored(streams.probed(probes_, data.nodes, compile_rpq(data.spec, "_*.begin._*.arrive._*")), _folder(spark))


QUERIES["stream_probes"] = _probe_stream
ORACLES["stream_probes"] = walk_sql("events", "_*.begin._*.arrive._*", "module = 'begin'", "module = 'end'", "SELECT event_id, 'u' || user_id AS run_id, 'u' || user_id || '.begin' AS src, 'u' || user_id || CASE WHEN event_type = 'error' THEN '.begin' ELSE '.end' END AS dst, event_type IS DISTINCT FROM 'error' AND hits.src IS NOT NULL AS holds FROM events LEFT JOIN hits ON hits.run_id = 'u' || user_id")


def _incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    data = run_of("documents", spark, sf_dir)
    new = data.nodes.where("module IN ('gather', 'sink')")
    return streams.matched_with(compile_rpq(data.spec, "_*.read._*"), data.nodes.where("module NOT IN ('gather', 'sink')"), new)


QUERIES["stream_incremental"] = _incremental
ORACLES["stream_incremental"] = walk_sql("documents", "_*.read._*", "TRUE", "module IN ('gather', 'sink')")
QUERIES["event_session_windows"] = lambda s, d: streams.sessions(runs.table(s, d, "events")).select("user_id", F.unix_micros("start").alias("first_us"), "n")
ORACLES["event_session_windows"] = f"{_FRESH}, s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS a FROM g) SELECT user_id, min(us) AS first_us, count(*) AS n FROM s GROUP BY user_id, a"


def _witnessed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relational.witnesses(run_of("example", spark, sf_dir), "_*.e._*").select("run_id", "src", "dst", F.array_join("tags", ".").alias("tags"))


def _witness_sql() -> str:
    c = CARRIERS["example"]
    dfa = rpq.compile_(rpq.parse("_*.e._*"), c.spec.tags)
    return f"""
WITH RECURSIVE edges AS (SELECT * FROM ({c.duckdb()}) AS e0), delta(q, tag, q2) AS (VALUES {", ".join(map(str, dfa.table()))}),
walk(src, node_id, q, tags) AS (
  SELECT node_id, node_id, 0, CAST([] AS VARCHAR[]) FROM (SELECT src AS node_id FROM edges UNION SELECT dst FROM edges) AS n
  UNION ALL SELECT w.src, e.dst, d.q2, list_append(w.tags, e.tag) FROM walk w JOIN edges e ON e.src = w.node_id JOIN delta d ON d.tag = e.tag AND d.q = w.q)
SELECT 'example' AS run_id, src, node_id AS dst, array_to_string((min({{'n': len(tags), 'tags': tags}})).tags, '.') AS tags FROM walk WHERE q IN ({", ".join(map(str, dfa.finals))}) GROUP BY src, node_id"""


QUERIES["witness_example"], ORACLES["witness_example"] = _witnessed, _witness_sql()


def _sql_front(spark: SparkSession, sf_dir: str) -> DataFrame:
    relational.register(spark, run_of("example", spark, sf_dir), {n: c.spec for n, c in CARRIERS.items()}, "example")
    return spark.sql("SELECT node_id, label_key, l.depth, l.kind, l.a, l.b, l.idx, spec_safe('example', concat(module, '*')) AS star_safe FROM example_node, LATERAL label_levels(label) AS l WHERE module IN ('a', 'e')")


#: The labels of the example's nodes, and the verdicts of their tags' stars.
_FRONT = [(n, "".join(f"{int(len(x) == 3):02x}{x[0]:04x}{x[1]:04x}{(x[2] if len(x) == 3 else 0):010x}" for x in label), d, int(len(e) == 3), e[0], e[1], e[2] if len(e) == 3 else 0, n[0] == "a") for n, label in runs._EXAMPLE_NODES.items() if n[0] in "ae" for d, e in enumerate(label)]
values("sql_front", "node_id, label_key, depth, kind, a, b, idx, star_safe", _FRONT, _sql_front)

# ---- languages and verdicts ----------------------------------------------------------------------
#: Words and whether the query has them.
_WORDS = [("a.(b|c)*.d?", w, x) for w, x in (("a", True), ("a b c", True), ("a d", True), ("b", False), ("a d d", False), ("", False), ("a b d", True), ("a z", False))]
_WORDS += [("(a.b)+|c", w, x) for w, x in (("a b", True), ("a b a b", True), ("c", True), ("a", False), ("c c", False))]


def _accepted(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for query in dict.fromkeys(q for q, _, _ in _WORDS):
        dfa = rpq.compile_(rpq.parse(query), tuple("abcdz"))
        x = spark.createDataFrame([(q, w) for q, w, _ in _WORDS if q == query], "query string, word string")
        x = x.select("query", "word", rpq.accepts_col(dfa, F.filter(F.split("word", " "), lambda t: t != "")).alias("accepted"))
        out = x if out is None else out.union(x)
    return out


values("membership", "query, word, accepted", _WORDS, _accepted)


# Queries over the roles of a conversation's successive turns, decided in tasks, one for each kind of succession.
_ROLES = """SELECT DISTINCT x, y, z FROM (
  SELECT role AS x, lead(role) OVER (PARTITION BY conv_id ORDER BY turn, role) AS y, lead(role, 2) OVER (PARTITION BY conv_id ORDER BY turn, role) AS z
  FROM {conversations} WHERE instr(role, chr(39)) = 0) AS r WHERE y IS NOT NULL AND z IS NOT NULL"""
#: Texts over tags x, y and z, and when both say the same, as SQL.
_SAME = [("x*", "(x|x.x)*", "TRUE"), ("(x|y)*", "(x*.y*)*", "TRUE"), ("x.y", "y.x", "x = y"), ("x+", "x.x*", "TRUE"), ("x?", "x", "FALSE")]
#: Texts over tags x, y and z, and when they are deterministic, as SQL.
_DETERMINISTIC = [("x.y*", "TRUE"), ("x.y|x.z", "y = z"), ("(x|y)*.x", "FALSE"), ("(x.y)*", "TRUE")]


def _named(text: str, tags: dict[str, str]) -> str:
    return "".join(f"'{tags[c]}'" if c in tags else c for c in text)


def _named_sql(text: str) -> str:
    return " || ".join(f"chr(39) || {c} || chr(39)" if c in "xyz" else f"'{c}'" for c in text)


def _over_roles(spark: SparkSession, sf_dir: str, decide: Callable[[dict[str, str]], list[tuple]], schema: str) -> DataFrame:
    columns = [c.split()[0] for c in schema.split(", ")]

    def one(batches):
        for pdf in batches:
            yield type(pdf)([row for x, y, z in zip(pdf["x"], pdf["y"], pdf["z"], strict=True) for row in decide({"x": x, "y": y, "z": z})], columns=columns)

    roles = spark.sql(_ROLES, conversations=runs.table(spark, sf_dir, "conversations"))
    return roles.mapInPandas(one, schema).distinct()


def _same(tags: dict[str, str]) -> list[tuple]:
    dfa = lambda text: rpq.compile_(rpq.parse(text), tuple(dict.fromkeys(tags.values())))
    texts = [(_named(a, tags), _named(b, tags)) for a, b, _ in _SAME]
    return [(a, b, rpq.equivalent(dfa(a), dfa(b))) for a, b in texts]


def _determined(tags: dict[str, str]) -> list[tuple]:
    return [(q, rpq.is_deterministic(rpq.parse(q))) for q in (_named(text, tags) for text, _ in _DETERMINISTIC)]


_ROLES_SQL = _ROLES.replace("{conversations}", "conversations")
QUERIES["equivalence"] = lambda s, d: _over_roles(s, d, _same, "one string, other string, same boolean")
ORACLES["equivalence"] = " UNION ".join(f"SELECT {_named_sql(a)} AS one, {_named_sql(b)} AS other, {when} AS same FROM ({_ROLES_SQL}) AS t" for a, b, when in _SAME)
QUERIES["determinism"] = lambda s, d: _over_roles(s, d, _determined, "query string, deterministic boolean")
ORACLES["determinism"] = " UNION ".join(f"SELECT {_named_sql(q)} AS query, {when} AS deterministic FROM ({_ROLES_SQL}) AS t" for q, when in _DETERMINISTIC)
_BATCH = [("A+", True, ""), ("e", False, "A"), ("_*.a._*", False, "A"), ("_*", True, "")]
values("safety_batch", "query, safe, module", _BATCH, lambda s, d: check_many(s, runs.EXAMPLE, [q for q, *_ in _BATCH]).select("query", "safe", F.coalesce("module", F.lit("")).alias("module")))
_TWICE = Spec.chain("S", [("S", "a S S b"), ("S", "c d")])
_LINEAR = [*((c, True) for c in CARRIERS), ("twice", False)]
values("strict_linearity", "carrier, linear", _LINEAR, lambda s, d: s.createDataFrame([*((c, CARRIERS[c].spec.is_strictly_linear()) for c in CARRIERS), ("twice", _TWICE.is_strictly_linear())], "carrier string, linear boolean"))
#: What the example's query can do inside each module: state on entering, state on leaving.
_INNER = [("A", 0, 1), ("A", 1, 1), ("S", 0, 0), ("S", 0, 1), ("S", 1, 1), *((m, q, q) for m in "Babcde" for q in (0, 1))]
QUERIES["augmented_example"] = _augmented
ORACLES["augmented_example"] = f"""
WITH t AS (SELECT count(*) AS n FROM conversations WHERE conv_id IS NOT NULL GROUP BY conv_id),
m AS (
  SELECT unnest(['S', 'B', 'c']) AS module, count(*) AS n FROM t UNION ALL SELECT 'A', sum(n) FROM t UNION ALL SELECT unnest(['a', 'd']), sum(n - 1) FROM t
  UNION ALL SELECT 'e', 2 * count(*) FROM t UNION ALL SELECT 'b', 3 * count(*) FROM t)
SELECT i.module, in_state, out_state, CAST(n AS BIGINT) AS executions FROM (VALUES {", ".join(map(str, _INNER))}) AS i(module, in_state, out_state) JOIN m ON m.module = i.module WHERE n > 0"""

# ---- labels, told in SQL from the tables ---------------------------------------------------------


def _at(k: int | str, i: int | str) -> str:
    """SQL for a position entry's twenty digits."""
    return f"printf('00%04x%04x0000000000', CAST({k} AS BIGINT), CAST({i} AS BIGINT))"


def _in_chain(cycle: int, idx: str) -> str:
    return f"printf('01%04x%04x%010x', {cycle}, 1, CAST({idx} AS BIGINT))"


_FORKS = "WITH d AS (SELECT source AS run_id, doc_id, lang = 'en' AS en, source || '.' || CAST(doc_id AS VARCHAR) AS n, row_number() OVER (PARTITION BY source ORDER BY doc_id) AS i, lead(doc_id) OVER (PARTITION BY source ORDER BY doc_id) IS NULL AS last FROM documents)"
_HANGS = f"CASE WHEN last THEN {_at(3, 1)} ELSE {_at(2, 3)} END"
_STAGES = "VALUES ('read', 1, 1), ('translate', NULL, 2), ('tokenise', 2, 3), ('write', 3, 4)"
_FORK_LABELS = f"""{_FORKS},
x AS (
  SELECT DISTINCT run_id, run_id || '.source' AS node_id, [{_at(1, 1)}] AS label FROM d
  UNION ALL SELECT DISTINCT run_id, run_id || '.sink', [{_at(1, 3)}] FROM d
  UNION ALL SELECT run_id, n || '.split', [{_at(1, 2)}, {_in_chain(1, "i")}, {_at(2, 1)}] FROM d WHERE NOT last
  UNION ALL SELECT run_id, n || '.gather', [{_at(1, 2)}, {_in_chain(1, "i")}, {_at(2, 4)}] FROM d WHERE NOT last
  UNION ALL SELECT run_id, n || '.' || m, [{_at(1, 2)}, {_in_chain(1, "i")}, {_HANGS}, CASE WHEN coalesce(en, FALSE) THEN {_at(4, "p")} ELSE {_at(5, "p5")} END]
  FROM d, ({_STAGES}) AS s(m, p, p5) WHERE p IS NOT NULL OR NOT coalesce(en, FALSE))"""
ORACLES["levels_documents"] = f"""{_FORK_LABELS},
y AS (SELECT run_id, node_id, label, unnest(range(len(label))) AS depth FROM x)
SELECT run_id, node_id, CAST(depth AS INTEGER) AS depth, array_to_string(label[1:depth], '') AS prefix,
       CASE label[depth + 2] WHEN {_at(2, 1)} THEN 'red' WHEN {_at(2, 4)} THEN 'blue' END AS colour FROM y"""


def _keys(carrier: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.with_keys(run_of(carrier, spark, sf_dir).nodes).select("run_id", "node_id", "label_key")


QUERIES["label_keys_documents"] = lambda s, d: _keys("documents", s, d)
ORACLES["label_keys_documents"] = f"{_FORK_LABELS} SELECT run_id, node_id, array_to_string(label, '') AS label_key FROM x"
_HOPS = "WITH p AS (SELECT 'h:' || regexp_extract(url, '^https?://([^/:?#]+)', 1) AS run_id, page_id, url LIKE 'http:%' AS plain FROM pages), q AS (SELECT *, run_id || '.p' || CAST(page_id AS VARCHAR) AS n, row_number() OVER (PARTITION BY run_id ORDER BY page_id) AS i, lead(page_id) OVER (PARTITION BY run_id ORDER BY page_id) IS NULL AS last FROM p)"
_HOP = f"{_at(1, 2)} || {_in_chain(1, 'i')} || CASE WHEN last THEN {_at(3, 1)} ELSE {_at(2, 1)} END"
_CRAWL_KEYS = f"""{_HOPS}
SELECT DISTINCT run_id, run_id || '.seed' AS node_id, {_at(1, 1)} AS label_key FROM q
UNION ALL SELECT DISTINCT run_id, run_id || '.stop', {_at(1, 3)} FROM q
UNION ALL SELECT run_id, n || '.fetch', {_HOP} || CASE WHEN plain THEN {_at(4, 1)} ELSE {_at(5, 1)} END FROM q
UNION ALL SELECT run_id, n || '.upgrade', {_HOP} || {_at(4, 2)} FROM q WHERE plain
UNION ALL SELECT run_id, n || '.store', {_HOP} || CASE WHEN plain THEN {_at(4, 3)} ELSE {_at(5, 2)} END FROM q"""
QUERIES["label_keys_crawl"], ORACLES["label_keys_crawl"] = lambda s, d: _keys("crawl", s, d), _CRAWL_KEYS


def _from_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The crawl's labels from a log of its derivation: who was expanded in which place of whose expansion."""
    p = runs.table(spark, sf_dir, "pages").select("page_id", "url").withColumn("host", F.regexp_extract("url", "^https?://([^/:?#]+)", 1))
    i, last = runs._rank(["host"], ["page_id"])
    p = p.select(F.concat(F.lit("h:"), "host").alias("run_id"), "page_id", F.col("url").startswith("http:").alias("plain"), i.alias("i"), last.alias("last"))
    row = lambda x, name, parent, prod, at, module: x.select("run_id", name.alias("exec"), parent.alias("parent"), prod.cast("int").alias("prod"), at.cast("int").alias("pos"), module.alias("module"))
    run, lit = F.col("run_id"), F.lit
    hops, hop = (F.concat(run, lit(x), F.col("i").cast("string")) for x in (".hops", ".hop"))
    one = p.where("i = 1")
    log = row(one, run, lit(None).cast("string"), lit(None), lit(None), lit("CRAWL"))
    for at, m in ((1, "seed"), (3, "stop")):
        log = log.union(row(one, F.concat(run, lit(f".{m}")), run, lit(1), lit(at), lit(m)))
    log = log.union(row(p, hops, F.when(F.col("i") == 1, run).otherwise(F.concat(run, lit(".hops"), (F.col("i") - 1).cast("string"))), F.when(F.col("i") == 1, 1).otherwise(2), lit(2), lit("HOPS")))
    log = log.union(row(p, hop, hops, F.when(F.col("last"), 3).otherwise(2), lit(1), lit("HOP")))
    kind = F.when(F.col("plain"), 4).otherwise(5)
    for m, at in (("fetch", lit(1)), ("upgrade", lit(2)), ("store", F.when(F.col("plain"), 3).otherwise(2))):
        x = p.where("plain") if m == "upgrade" else p
        log = log.union(row(x, F.concat(run, lit(".p"), F.col("page_id").cast("string"), lit(f".{m}")), hop, kind, at, lit(m)))
    return streams.with_keys(simulate.labels_from_log(log, runs.CRAWL)).select("run_id", "node_id", "label_key")


QUERIES["labels_from_log"], ORACLES["labels_from_log"] = _from_log, _CRAWL_KEYS
_STEP = f"{_at(1, 2)} || {_in_chain(1, '2 * a - 1')} || {_at(2, 1)}"
ORACLES["stream_labels"] = f"""
WITH e AS (SELECT 'u' || CAST(user_id AS VARCHAR) AS run_id, event_type, event_id, epoch_us(ts) AS us FROM events),
g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY run_id ORDER BY us, event_id) <= 43200000000 THEN 0 ELSE 1 END AS fresh FROM e),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY run_id ORDER BY us, event_id ROWS UNBOUNDED PRECEDING) AS a FROM g),
r AS (SELECT *, row_number() OVER (PARTITION BY run_id, a ORDER BY us, event_id) AS b FROM s),
k(event_type, prod, i, module) AS (VALUES ('click', 9, 1, 'click'), ('click', 9, 2, 'ack'), ('view', 10, 1, 'view'), ('view', 10, 2, 'ack'), ('signup', 11, 1, 'signup'), ('signup', 11, 2, 'verify'), ('signup', 11, 3, 'ack'),
  ('purchase', 12, 1, 'purchase'), ('purchase', 12, 2, 'charge'), ('purchase', 12, 3, 'ship'), ('purchase', 12, 4, 'ack'), ('error', 13, 1, 'error'), ('error', 13, 2, 'retry'), ('error', 13, 3, 'ack'))
SELECT DISTINCT run_id, run_id || '.begin' AS node_id, 'begin' AS module, {_at(1, 1)} AS label_key FROM e
UNION ALL SELECT run_id, run_id || '.s' || CAST(a AS VARCHAR) || '.arrive', 'arrive', {_STEP} || {_at(5, 1)} FROM r WHERE b = 1
UNION ALL SELECT run_id, run_id || '.s' || CAST(a AS VARCHAR) || '.e' || CAST(b AS VARCHAR) || '.' || module, module, {_STEP} || {_at(5, 2)} || {_in_chain(2, '2 * b - 1')} || {_at(6, 1)} || {_at("prod", "i")}
FROM r JOIN k USING (event_type)"""
_PLACES = sum(len(p.body) for p in runs.ORDERS.productions)
ORACLES["measure_label_lengths"] = f"""
WITH e AS (SELECT * FROM ({CARRIERS["orders"].duckdb()}) AS e0),
n AS (SELECT run_id, count(*) AS nodes FROM (SELECT run_id, src FROM e UNION SELECT run_id, dst FROM e) AS u GROUP BY run_id),
o AS (SELECT 'c' || CAST(o_custkey AS VARCHAR) AS run_id, count(*) AS orders FROM orders GROUP BY o_custkey),
l AS (SELECT 'c' || CAST(o_custkey AS VARCHAR) AS run_id, max(c) AS lines FROM orders JOIN (SELECT l_orderkey, count(*) AS c FROM lineitem GROUP BY l_orderkey) AS x ON l_orderkey = o_orderkey GROUP BY o_custkey),
w AS (SELECT ceil(log2(1 + {_PLACES})) AS place, ceil(log2(1 + greatest((SELECT max(orders) FROM o), (SELECT coalesce(max(lines), 0) FROM l)))) AS chain)
SELECT n.run_id, nodes, CASE WHEN lines IS NULL THEN 4 ELSE 7 END AS entries, CAST(CASE WHEN lines IS NULL THEN 4 * place + chain ELSE 7 * place + 2 * chain END AS INTEGER) AS bits, round(log2(nodes), 3) AS log2_nodes
FROM n LEFT JOIN l USING (run_id), w"""
