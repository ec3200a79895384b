"""Operators against brute force on larger fixtures, against SQL on the given tables, and the pipeline's edge cases."""

import os
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from wfpath.llm import quality_model, registry, shared, suffix_dedup, url_filter, vector_dedup

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size int, v string"


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    for f in os.listdir(SF):
        con.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SF}/{f}'")
    return con


def test_source_mix_against_sql(spark, duck):
    df = registry.QUERIES["op1_source_mix"](spark, SF)
    cols = sorted(df.columns)
    got = sorted(map(repr, (tuple(r) for r in df.select(*cols).collect())))
    assert got == sorted(map(repr, duck.sql(f"SELECT {', '.join(cols)} FROM ({registry.ORACLES['op1_source_mix']}) AS t").fetchall()))


def test_base_counts_against_sql(spark, duck):
    got = {r["doc_id"]: (r["n_words"], r["word_chars"], r["n_symbols"]) for r in registry.QUERIES["op2_quality_rules"](spark, SF).collect()}
    want = duck.sql(r"""SELECT doc_id, len(regexp_extract_all(t, '[^\x20\x09-\x0D]+')), length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')),
                        length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) FROM (SELECT doc_id, coalesce(text, '') AS t FROM documents)""").fetchall()
    assert got == {i: (a, b, c) for i, a, b, c in want}


def test_window_removal_against_sql(spark, duck):
    """Windows of 50 words by a plain join of lists, in DuckDB."""
    want = duck.sql(r"""
        WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
        s AS (SELECT doc_id, unnest(range(1, len(words) - 48)) AS p, words FROM w WHERE len(words) >= 50),
        k AS (SELECT doc_id, p, array_to_string(words[p:p + 49], ' ') AS win FROM s),
        m AS (SELECT win, min(doc_id) AS least FROM k GROUP BY win HAVING min(doc_id) <> max(doc_id)),
        g AS (SELECT DISTINCT doc_id, unnest(range(p, p + 50)) AS at FROM k JOIN m USING (win) WHERE doc_id > least)
        SELECT w.doc_id, len(words), coalesce(n, 0) FROM w LEFT JOIN (SELECT doc_id, count(*) AS n FROM g GROUP BY doc_id) USING (doc_id)""").fetchall()
    got = {(r["doc_id"], r["n_words"], r["n_removed"]) for r in registry.QUERIES["op10_substring_dedup"](spark, SF).collect()}
    assert got == set(want) and any(n for *_, n in want)


def test_repeated_bytes_by_brute_force(spark):
    """The query on whole tables, against a dictionary of all 200-byte strings."""
    rows = {r["doc_id"]: (r["text"] or "").encode() for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    times = {}
    for i, t in rows.items():
        for j in range(len(t) - 199):
            h = hash(t[j : j + 200])
            times[h] = times.get(h, 0) + 1
    for r in registry.QUERIES["op7_suffix_dedup"](spark, SF).collect():
        t = rows[r["doc_id"]]
        gone = np.zeros(len(t) + 1, np.int64)
        for j in range(len(t) - 199):
            if times[hash(t[j : j + 200])] > 1:
                gone[j] += 1
                gone[j + 200] -= 1
        gone = np.cumsum(gone[:-1]) > 0
        assert (r["n_bytes"], r["n_removed"], r["n_spans"]) == (len(t), gone.sum(), int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum()))


def test_large_and_long_texts(spark):
    """Texts over the parts' size, and a collection over the largest one: the same bytes go as by a dictionary."""
    rng = np.random.default_rng(2)
    passage = rng.integers(97, 123, 700).astype(np.uint8).tobytes().decode()
    long = rng.integers(97, 123, suffix_dedup.PART + 5000).astype(np.uint8).tobytes().decode()
    rows = [(1, long[:-300] + passage), (2, "X" * 100 + passage + "Y" * 20), (3, long[suffix_dedup.PART - 400 : suffix_dedup.PART + 400])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc"]: suffix_dedup.kept_bytes(r["text"].encode(), r["marks"], 200)[1] for r in suffix_dedup.marked(docs).collect()}
    assert got == {1: 700 + 800, 2: 700, 3: 800}


def test_rules_on_urls_by_brute_force(spark):
    rows = spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "url").collect()
    verdicts = [("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block")]
    got = {r["page_id"]: r for r in registry.QUERIES["op4_url_filter"](spark, SF).collect()}
    assert len(got) == len(rows)
    for page, url in rows:
        m = re.match(r"[\s\S]*?://([^/?#]*)([^?#]*)", url or "")
        host, path = (re.sub("[A-Z]", lambda c: c[0].lower(), m[1]), m[2]) if m else ("", "")
        fits = [(r, v) for r, v in verdicts if (host + path).startswith(r) or any((host[k + 1 :] + path).startswith(r) and r.split("/")[0] == host[k + 1 :] for k, c in enumerate(host) if c == ".")]
        fits = [(r, v) for r, v in fits if (host == r.split("/")[0] or host.endswith("." + r.split("/")[0])) and path.startswith("/" + r.split("/", 1)[1])]
        best = max(fits, key=lambda x: len(x[0]), default=(None, None))
        assert (got[page]["host"], got[page]["path"], got[page]["rule"]) == (host, path, best[0])
        assert got[page]["verdict"] == best[1] if best[1] else got[page]["verdict"] in ("allow", "block")


def test_url_model_learns(spark):
    rows = [(i, f"http://{'spam' if i % 2 else 'news'}{i % 37}.org/{'casino-win' if i % 2 else 'article'}/{i}") for i in range(600)]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    labelled = spark.createDataFrame([(f"{'spam' if i % 2 else 'news'}{i}.org", f"/{'casino-win' if i % 2 else 'article'}/{i}", i % 2 == 1) for i in range(1000, 1200)], "host string, path string, block boolean")
    got = {r["page_id"]: r["verdict"] for r in url_filter.filtered(pages, labelled=labelled).collect()}
    assert all(got[i] == ("block" if i % 2 else "allow") for i, _ in rows)
    drawn = url_filter.labelled_sample(labelled, 50)
    assert 0 < len(drawn[0]) < 120 and drawn[0] == url_filter.labelled_sample(labelled, 50)[0]


def test_quality_model_on_held_out_rows(spark):
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet("/root/testdata/sf0.01/labels.parquet").collect()}
    got = {r["doc_id"]: r for r in registry.QUERIES["op3_quality_model"](spark, "/root/testdata/sf0.01").collect()}
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 3 == 1) and 0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for i, r in got.items())
    held = [i for i, r in got.items() if r["held_out"] and i in labels]
    assert sum(got[i]["predicted"] == labels[i] for i in held) >= 0.95 * len(held) > 50
    # labels of held-out rows don't matter
    some = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").where("doc_id < 300")
    marks = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    turned = marks.withColumn("quality", F.when(F.crc32(F.col("doc_id").cast("string")) % 3 == 1, 1 - F.col("quality")).otherwise(F.col("quality")))
    a, b = ({r["doc_id"]: r["score"] for r in quality_model.scored(some, x).collect()} for x in (marks, turned))
    assert a == b


def test_vectors_over_pieces_by_brute_force(spark, monkeypatch):
    """Planted links at 0.9 and above among lists that are cut into several pieces; components and counts of what is found."""
    monkeypatch.setattr(vector_dedup, "PIECE", 64)
    monkeypatch.setattr(vector_dedup, "VISITS", 128)
    rng = np.random.default_rng(21)
    base = rng.normal(size=(1500, 32))
    unit = base / np.linalg.norm(base, axis=1, keepdims=True)
    aside = rng.normal(size=(300, 32))
    aside -= (aside * unit[:300]).sum(1, keepdims=True) * unit[:300]
    aside /= np.linalg.norm(aside, axis=1, keepdims=True)
    cosine = rng.uniform(0.86, 0.99, 300)[:, None]
    x = np.vstack([unit, cosine * unit[:300] + np.sqrt(1 - cosine**2) * aside, unit[:40]]).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    got = {r["vec_id"]: r for r in vector_dedup.near_duplicates(df).collect()}
    y = x.astype(float)
    y /= np.linalg.norm(y, axis=1, keepdims=True)
    link = y @ y.T >= 0.9
    np.fill_diagonal(link, False)
    found = sum(r["n_links"] for r in got.values())
    assert 0.9 * link.sum() <= found <= link.sum() > 300
    root = shared.local_components(len(y), *np.nonzero(link))
    right = sum(got[i]["component_id"] == root[i] for i in range(len(y)))
    assert right >= 0.97 * len(y) and all(root[got[i]["component_id"]] == root[i] for i in range(len(y)))
    assert all(r["kept"] == (r["component_id"] == i) for i, r in got.items())


def test_hot_keys_meet_by_broadcast(spark):
    rows = spark.range(3000).select(F.when(F.col("id") % 3 == 0, -1).otherwise(F.col("id")).alias("k"), F.col("id").alias("x"))
    counted = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.min("x").alias("least"))
    got = shared.joined_by_count(rows, counted, ["k"], "n").collect()
    assert sorted(r["x"] for r in got) == list(range(3000)) and all(r["least"] == (0 if r["k"] == -1 else r["x"]) for r in got)
    assert shared.joined_by_count(rows.limit(0), counted.limit(0), ["k"], "n").count() == 0


def tables(spark, folder, docs, labels):
    docs.write.parquet(f"file://{folder}/documents.parquet")
    labels.write.parquet(f"file://{folder}/labels.parquet")
    return f"file://{folder}"


def test_pipeline_edge_cases(spark, tmp_path):
    """Nulls, repeated ids, empty texts, clashing columns: each stage keeps the columns, each decision takes effect."""
    text = " ".join(f"word{i}" for i in range(120))
    other = " ".join(f"other{i}" for i in range(150))
    rows = [(1, text, "en", "a", 1, 1, "x"), (2, text, "en", "a", 1, 1, "x"), (3, None, None, None, None, None, None), (4, "", "en", "b", 0, 1, ""), (None, other, "de", "b", 1, 1, "y"), (5, "too short", "en", "b", 1, 1, "z"), (6, "# " * 200, "en", "a", 1, 1, "s"), (7, " ".join(f"long{i}" for i in range(9000)), "fr", None, 1, 1, "l"), (7, other + " and more", "fr", "c", 1, 1, "l")]
    sf = tables(spark, tmp_path, spark.createDataFrame(rows, SCHEMA), spark.createDataFrame([(1, 1, 0), (6, 0, 0), (None, None, None)], "doc_id long, quality int, toxic int"))
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = corpus_pipeline.quality(spark, docs, sf)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {1, 2, None, 7}
    single = shared.materialised(corpus_pipeline.near_duplicates(spark, kept, sf))
    assert single.columns == docs.columns and {r["doc_id"] for r in single.collect()} == {1, None, 7} or {r["doc_id"] for r in single.collect()} == {1, 7}
    cut = corpus_pipeline.repeated_strings(spark, single, sf)
    assert cut.columns == docs.columns and cut.count() == single.count()
    mixed = corpus_pipeline.mix(spark, cut, sf)
    assert mixed.columns == docs.columns
    out = corpus_pipeline.run(spark, sf).collect()
    assert out and all(0 < r["length"] <= 4096 for r in out)


def test_pipeline_of_empty_tables(spark, tmp_path):
    sf = tables(spark, tmp_path, spark.createDataFrame([], SCHEMA), spark.createDataFrame([], "doc_id long, quality int, toxic int"))
    assert corpus_pipeline.run(spark, sf).count() == 0
