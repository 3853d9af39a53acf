"""Worked miniatures, dual implementations and invariants of the extraction engine."""

import json
import os
import random

import pytest
from pyspark.sql import functions as F

from fieldlift import studies, workloads as w  # noqa: F401 (studies registers its queries)
from fieldlift.functions import columns as c
from fieldlift.functions.shred import html_nodes, node_table, xml_nodes
from fieldlift.operators import archive, audit, measures, pairing, stages
from fieldlift.operators import dictionary as dicts
from fieldlift.plans import loader, mapping
from fieldlift.sources import notices as src

DICT = [("en", k, None, s, k, False) for k, s in (("title", "Title of the notice"), ("price", "Price"), ("who", "Contractor"))]
DICT_SCHEMA = "lang string, key_id string, parent_key_id string, surface string, elem_name string, is_static boolean"
FACTS = {("title", "A new bridge"), ("price", "1m"), ("who", "Some firm")}
LAYOUTS = {
    "table": "<table><tr><td>Title of the notice</td><td>A new bridge</td></tr><tr><td>Price</td><td>1m</td></tr><tr><td>Contractor</td><td>Some firm</td></tr></table>",
    "sections": "<div><h3>1.1 Title of the notice</h3><p>A new bridge</p></div><div><h3>2. Prices</h3><p>1m</p></div><div><h3>Contractor</h3><p>Some firm</p></div>",
    "flat": "<div><p>Title of the notice : A new bridge</p><p>Price 1m</p><p>Contractor &rarr; Some firm</p></div>",
}


def frame(spark, html):
    return spark.createDataFrame([("1", "s", "en", html)], "doc_id string, source string, lang string, body string")


@pytest.mark.parametrize("layout", LAYOUTS)
def test_three_layouts_give_the_same_pairs(spark, layout):
    d = spark.createDataFrame(DICT, DICT_SCHEMA)
    nodes = node_table(frame(spark, LAYOUTS[layout]), "body", ("doc_id", "source", "lang"))
    nodes = pairing.split_inline(nodes, d) if layout == "flat" else nodes
    got = pairing.pair_values(nodes, d, theta_path=0.4)
    assert {(r.key_id, r.value) for r in got.collect()} == FACTS


def test_scan_implementations_agree(spark, data):
    d = src.dictionary(spark)
    nodes = pairing.prepared_nodes(src.notices(spark, data, layouts=("widgets",)), d, simplify=True).filter("doc_id % 5 = 0")
    rows = [sorted(map(tuple, pairing.pair_values(nodes, d, impl=i).select("doc_id", "key_id", "value", "value_no").collect())) for i in ("window", "fold", "arrow")]
    assert rows[0] == rows[1] == rows[2] and rows[0]


def test_every_node_has_one_role(spark):
    d = spark.createDataFrame(DICT[:2], DICT_SCHEMA)
    nodes = node_table(frame(spark, "<p>stray</p>" + LAYOUTS["table"]), "body", ("doc_id", "source", "lang"))
    s = pairing.scan(nodes, pairing.match_keys(nodes, d))
    roles = {r.role: r.n for r in s.groupBy("role").agg(F.count("*").alias("n")).collect()}
    assert sum(roles.values()) == 7 and roles["key"] == 2
    assert {r.reason for r in pairing.unmatched_of(s).collect()} >= {"before any key"}


def test_path_spellings():
    html = '<html><body><div></div><div id="x"><p>a</p></div></body></html>'
    node = html_nodes(html)[0]
    assert node[3] == ["html", "body", "div", "p"]
    assert node[4] == ["html1", "body1", "div2", "p"]
    assert node[5] == ["html1", "body1", "div2.x", "p"]
    assert html_nodes(html, numbering="siblings", number_leaf=True)[0][4] == ["html1", "body1", "div2", "p1"]


def test_tag_soup_ends():
    nodes = html_nodes("<ul><li>a<li>b</ul><p>c<p><b>d<table><tr><td>e<td>f</table><script>if (a</p>b)</script>g")
    assert [n[-1] for n in nodes] == ["a", "b", "c", "d", "e", "f", "g"]
    assert xml_nodes("<a><b></a>") is None and xml_nodes("<a x='1'><b>t</b></a>")[0][3] == ["a", "@x"]


CUT_OFF = "<html><head><title>A &amp; b&amp</title></head><body><article><h1>A &amp; b&amp</h1><p>c</p></article></body></html>"


def cut_off_pages(spark, tmp_path):
    """Two pages; a title ends inside a reference, as those of longer tables do."""
    rows = [(1, "https://a.example/1", CUT_OFF), (2, "https://a.example/2", CUT_OFF.replace("b&amp", "&lt;b&gt; &#38; c &ampx"))]
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    return str(tmp_path)


def test_open_references():
    assert html_nodes("<p>a&amp</p>")[0][7] == "a&" and html_nodes("<p>a&amp</p>", closed=True)[0][7] == "a&amp"
    assert html_nodes("<p>&lt;&#65;&#x42;&nosuch; &amp;amp; &</p>", closed=True)[0][7] == "<AB&nosuch; &amp; &"


def test_page_titles_keep_open_references(spark, tmp_path):
    got = w.QUERIES["page_titles"](spark, cut_off_pages(spark, tmp_path)).collect()
    assert {(r.doc_id, r.value) for r in got} == {("1", "A & b&amp"), ("2", "A & <b> & c &ampx")}


def test_keyless_title_keeps_open_references(spark, tmp_path):
    got = w.QUERIES["keyless_title"](spark, cut_off_pages(spark, tmp_path)).collect()
    assert {(r.doc_id, r.value) for r in got} == {("1", "A & b&amp"), ("2", "A & <b> & c &ampx")}


def test_similarities_match_plain_python(spark):
    paths = [(["a", "b", "c"], ["a", "b", "d", "c"]), ([], []), (["a"], []), (["x", "y"], ["x", "y"]), (["a", "b"], ["c", "d"])]
    df = spark.createDataFrame([(i, p, q) for i, (p, q) in enumerate(paths)], "i int, p array<string>, q array<string>")
    got = df.select("i", c.path_edit_sim("p", "q").alias("e"), *[c.path_prefix_sim("p", "q", n).alias(n) for n in ("max", "min", "mean")]).orderBy("i").collect()
    for (p, q), r in zip(paths, got):
        assert r.e == pytest.approx(pairing.local_similarity("edit", p, q))
        for n in ("max", "min", "mean"):
            assert r[n] == pytest.approx(pairing.local_similarity("prefix", p, q, n))


def test_ambiguous_leaf_has_two_key_paths(spark):
    d = spark.createDataFrame([("en", "buyer", None, "The contract details", "buyer", False), ("en", "firm", None, "Contractor", "firm", False), ("en", "buyer/name", "buyer", "Name", "name", False), ("en", "firm/name", "firm", "Name", "name", False)], DICT_SCHEMA)
    html = "<div><h2>Section 1: The contract details</h2><h3>Name</h3><p>A bridge</p><h2>2. Contractor</h2><h3>Name</h3><p>Some firm</p></div>".replace("Section 1: ", "1. ")
    nodes = node_table(frame(spark, html), "body", ("doc_id", "source", "lang"))
    assert {(r.key_path, r.value) for r in pairing.pair_values_hier(nodes, d).collect()} == {("buyer/name", "A bridge"), ("firm/name", "Some firm")}


def test_repeated_items_become_a_list(spark):
    d = spark.createDataFrame([("en", "name", None, "Name", "name", False)], DICT_SCHEMA)
    nodes = pairing.split_inline(node_table(frame(spark, "<ul><li>Name: Ada</li><li>Name: Bob</li><li>Name: Cy</li></ul>"), "body", ("doc_id", "source", "lang")), d)
    xml = pairing.emit_xml(pairing.pair_values(nodes, d, theta_path=0.3), d).first().xml
    assert xml == "<document><list_of_name><name>Ada</name><name>Bob</name><name>Cy</name></list_of_name></document>"


def test_blocked_pairs_equal_all_pairs(spark, data):
    names = spark.read.parquet(f"{data}/part.parquet").select(F.lit("en").alias("lang"), F.col("p_name").alias("text")).distinct()
    extra = spark.createDataFrame([("en", t) for t in ("ab", "abc", "a", "aaaa", "aaaaa", "Buyers", "Buyer", "Total values", "Total value")], "lang string, text string")
    both = names.union(extra)
    for theta in (0.6, 0.8):
        a = {(r.a, r.b) for r in dicts.similar_pairs(both, theta).collect()}
        assert a == {(r.a, r.b) for r in dicts.similar_pairs(both, theta, blocked=False).collect()} and a


def test_components_equal_union_find(spark):
    edges = [("a", "b"), ("b", "c"), ("d", "e"), ("z", "y"), ("c", "x")]
    nodes = spark.createDataFrame([(n,) for n in "abcdexyzq"], "node string")
    got = {r.node: r.root for r in dicts.components(nodes, spark.createDataFrame(edges, "a string, b string")).collect()}
    assert got == {"a": "a", "b": "a", "c": "a", "x": "a", "d": "d", "e": "d", "y": "y", "z": "y", "q": "q"}


def test_dictionary_edits(spark):
    d = spark.createDataFrame(DICT, DICT_SCHEMA)
    edits = spark.createDataFrame([("add", "en", "price", "Amount", None), ("remove", "en", "who", "Contractor", None), ("rename", "en", "title", None, "heading")], "op string, lang string, key_id string, surface string, target string")
    got = {(r.key_id, r.surface, r.elem_name) for r in dicts.edit_dictionary(d, edits).collect()}
    assert got == {("price", "Price", "price"), ("price", "Amount", "price"), ("title", "Title of the notice", "heading")}


def test_repairs(spark):
    xml = "<r><lot_1><item>a</item></lot_1><lot_2><item>b</item></lot_2><s><lot_3_item>c</lot_3_item></s></r>"
    nodes = node_table(frame(spark, xml), "body", ("doc_id", "source", "lang"), "xml")
    assert [r.plain for r in stages.fold_numbered(nodes).orderBy("ord").collect()][:2] == [["r", "lot", "item"]] * 2
    assert stages.nest_numbered(nodes).orderBy("ord").collect()[2].plain == ["r", "s", "lot", "item"]


def test_unpack(spark):
    import gzip
    import io
    import zipfile

    z = io.BytesIO()
    with zipfile.ZipFile(z, "w") as f:
        f.writestr("x.txt", "1")
        f.writestr("y.txt", "2")
    rows = [("a", "a.zip", z.getvalue()), ("b", "b.txt.gz", gzip.compress(b"3")), ("c", "c.rar", b"Rar!abc"), ("d", "d", b"4"), ("e", "e.zip", b"PKbroken")]
    got = {(r.item_id, r.member, r.status.split(":")[0], bytes(r.body or b"")) for r in stages.unpack(spark.createDataFrame(rows, "item_id string, name string, body binary")).collect()}
    assert got == {("a", "x.txt", "ok", b"1"), ("a", "y.txt", "ok", b"2"), ("b", "b.txt", "ok", b"3"), ("c", "c.rar", "unsupported", b""), ("d", "d", "ok", b"4"), ("e", "e.zip", "damaged", b"")}


def test_json_and_text_trees(spark):
    docs = frame(spark, '{"a": [{"b": 1}, {"b": true}], "c": "x"}')
    got = [(r.plain[1:], r.text) for r in stages.json_to_tree(docs).orderBy("ord").collect()]
    assert got == [(["a", "b"], "1"), (["a", "b"], "true"), (["c"], "x")]
    assert [r.text for r in stages.txt_to_tree(frame(spark, "l1\n\nl2")).collect()] == ["l1", "l2"]


def test_mapping_miniature(spark):
    xml = "<n><t>One</t><ok>ja</ok><f><m>5</m></f><part no='7'/><part no='8'><x>q</x></part></n>"
    target = mapping.load_target(json.dumps({"entities": [{"name": "doc", "fields": {"title": "text", "fine": "text"}}, {"name": "money", "fields": {"sum": "text"}, "links": {"doc_id_": "doc", "doc_id": "doc"}}, {"name": "bit", "fields": {"no": "text", "x": "text"}, "links": {"doc_id": "doc"}}, {"name": "gone", "fields": {"y": "text"}, "links": {"bit_id": "bit"}}]}).replace('"doc_id_": "doc", ', ""))
    m = mapping.load_mapping(json.dumps({"version": 1, "map": [{"entity": "doc", "path": "/n", "fields": {"title": ["head", "t"], "fine": "ok"}, "recodes": {"fine": {"ja": "yes"}}, "children": [{"entity": "bit", "path": "part", "fields": {"no": "@no", "x": "x"}, "children": [{"entity": "gone", "path": ".", "fields": {"y": "y"}}]}]}]}))
    nodes = node_table(frame(spark, xml), "body", ("doc_id", "source", "lang"), "xml")
    e = loader.extract_entities(nodes, m, target)
    doc = e["doc"].collect()
    assert [(r.title, r.fine) for r in doc] == [("One", "yes")]
    bits = e["bit"].orderBy("no").select("no", "x").collect()
    assert [tuple(r) for r in bits] == [("7", None), ("8", "q")] and e["gone"].count() == 0


def test_path_dialect():
    ok = lambda p, s: bool(__import__("re").search(mapping.compile_path(p).pattern, s))
    assert ok("/a//b", "/a/x/y/b") and ok("/a/*/b", "/a/q/b") and not ok("/a/*/b", "/a/b") and ok("/a/~lot_\\d+/@no", "/a/lot_12/@no")
    assert mapping.compile_path("/a/b[2]").index == 2 and mapping.compile_path("/a/b/text()").text == "/a/b"


def test_flush_order():
    from fieldlift.studies import FULL_SCHEMA

    levels = loader.flush_order({k: set(v.split()) for k, v in FULL_SCHEMA.items()})
    assert (len(FULL_SCHEMA), sum(len(v.split()) for v in FULL_SCHEMA.values())) == (33, 59)
    assert [len(x) for x in levels] == [3, 1, 2, 4, 12, 10, 1] and levels[0] == ["address", "corrigenda", "price"] and levels[6] == ["bid_documents"]
    with pytest.raises(ValueError, match="cycle: a -> b -> a"):
        loader.flush_order({"a": {"b"}, "b": {"a"}})


def test_flush_writes_in_order(spark, data, tmp_path):
    from fieldlift.sources.sinks import file_sink

    e = w.entities(spark, data)
    done = loader.flush(e, loader.target_order(mapping.load_target(w.TARGET)), file_sink(str(tmp_path)))
    assert done.index("price") < done.index("lot") < done.index("lot_object")
    assert measures.stored_sizes(spark, f"{tmp_path}/lot").count() == 6


def test_inventory_and_amend(spark):
    xml = "<a><b>1</b><b>2</b><c/><d x='y'>3</d></a>"
    nodes = node_table(frame(spark, xml), "body", ("doc_id", "source", "lang"), "xml")
    inv = audit.path_inventory(nodes)
    assert {(r.path, r.n) for r in inv.collect()} == {("/a/b", 2), ("/a/d", 1), ("/a/d/@x", 1)}
    start = spark.createDataFrame([("^/a/b$",)], "pattern string")

    def reviewer(queue):
        top = queue.limit(1)
        return top.select(F.concat(F.lit("^"), "path", F.lit("$")).alias("pattern")), top.select("path").limit(0)

    done, history = audit.amend(inv, start, reviewer)
    assert [h[1] for h in history] == [2, 1, 0]


def test_occupation_sums_to_one(spark):
    rows = spark.createDataFrame([("s", "a", 72), ("s", "b", 28), ("s", "c", 0)], "source string, entity string, rows long")
    got = {r.entity: (r.r, r.balanced) for r in measures.occupation(rows).collect()}
    assert got["a"][0] == pytest.approx(0.72) and sum(v[0] for v in got.values()) == pytest.approx(1) and got["c"] == (0.0, pytest.approx(1 / 3))


def test_charsets():
    text = "Numéro"
    assert archive.decode_bytes(text.encode("latin-1"), "iso-8859-1", None, ())[:2] == (text, "iso8859-1")
    assert archive.decode_bytes(text.encode(), None, None, ("cp1252",)) == (text, "utf-8", True)
    assert archive.decode_bytes("Номер".encode("cp1251"), "utf-8", None, ("cp1251",))[:1] == ("Номер",)


def test_conversions(spark):
    df = spark.createDataFrame([("ja", "de", "03.02.2001"), ("nope", "en", "2001-02-03"), (None, "fr", "x")], "b string, lang string, d string")
    got = df.select(c.to_bool("b", "lang").alias("b"), c.to_date_any("d").cast("string").alias("d"), c.strip_numbering(F.lit("II.1) Name")).alias("s")).collect()
    assert [r.b for r in got] == [True, None, None] and got[0].d == got[1].d == "2001-02-03 00:00:00" and got[2].d is None and got[0].s == "Name"


def test_registered_sql_matches(spark, data):
    import duckdb

    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "labels", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    for name in ("canonical_urls", "query_windows", "pairs_table", "path_inventory", "map_lots", "entity_counts"):
        df = w.queries()[name](spark, data)
        cols = sorted(df.columns)
        mine = sorted(str(tuple(r[x] for x in cols)) for r in df.collect())
        cur = con.execute(w.oracle_sql()[name])
        names = [d[0] for d in cur.description]
        theirs = sorted(str(tuple(r[names.index(x)] for x in cols)) for r in cur.fetchall())
        assert mine == theirs, name


def test_plan_of_the_scan(spark, data):
    d = src.dictionary(spark)
    nodes = pairing.prepared_nodes(src.notices(spark, data, layouts=("table",)), d)
    plan = pairing.pair_values(nodes, d)._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan


def test_segment_join_equals_all_pairs(spark):
    rnd = random.Random(5)
    words = ["", "a", "ab", "abc", "Country", "Countrys", "Cuontry"]
    for _ in range(160):
        words.append("".join(rnd.choice("abcd ") for _ in range(rnd.randrange(0, 14))))
    df = spark.createDataFrame([("en", w) for w in dict.fromkeys(words)], "lang string, text string")
    for theta in (0.35, 0.5, 0.6, 0.8, 0.95):
        a = {tuple(r) for r in dicts.similar_pairs(df, theta).filter("a <> ''").collect()}
        b = {tuple(r) for r in dicts.similar_pairs(df, theta, blocked=False).filter("a <> ''").collect()}
        assert a == b, theta
    plan = dicts.similar_pairs(df, 0.6)._jdf.queryExecution().optimizedPlan().toString()
    assert "key" in plan


def test_large_dictionaries_match_alike(spark):
    rnd = random.Random(6)
    surfaces = ["".join(rnd.choice("abcdefg") for _ in range(rnd.randrange(3, 16))) for _ in range(80)]
    d = spark.createDataFrame([("en", f"k{i}", None, s, "e", False) for i, s in enumerate(surfaces)], "lang string, key_id string, parent_key_id string, surface string, elem_name string, is_static boolean")
    texts = [s[:k] + rnd.choice("abz") + s[k + 1 :] for s in surfaces for k in (0, 2)] + surfaces + ["zzz", "x" * 50]
    nodes = spark.createDataFrame([("en", t) for t in texts], "lang string, text string")
    small, large = (sorted(map(tuple, pairing.match_keys(nodes, d, 0.7, compared=n).collect())) for n in (512, 0))
    assert small == large and len(small) > 80


def test_pools_and_levels(spark):
    rows = spark.range(2300).repartition(7)
    sizes = [len(p) for p in loader.pooled(rows, 500).rdd.glom().collect()]
    assert sum(sizes) == 2300 and max(sizes) <= 500
    order, at = [["a", "b"], ["c"]], []
    done = loader.flush({n: rows for n in "abc"}, order, lambda n, df: at.append((n, df.count())), batch_rows=1000)
    assert sorted(done[:2]) == ["a", "b"] and done[2] == at[2][0] == "c" and {n for _, n in at} == {2300}


def test_random_review_needs_more_rounds(spark):
    inv = spark.createDataFrame([("s", f"/p{k}", 2 ** (12 - k)) for k in range(12)], "source string, path string, n long")
    rounds = {k: audit.rounds_to_coverage(inv, k, 2, 0.9) for k in ("frequency", "weighted", "random", "tail")}
    assert rounds["frequency"] == 2 and rounds["tail"] == 6 and rounds["frequency"] <= rounds["weighted"] <= 6 and rounds["frequency"] <= rounds["random"] <= 6


def test_cleanup_and_chain(spark, tmp_path):
    path = str(tmp_path / "run")
    spark.range(3).write.parquet(path)
    assert stages.cleanup(spark, path) and not os.path.exists(path) and not stages.cleanup(spark, path)
    stages.register_stage("keep_small", lambda df, limit: df.filter(f"id < {limit}"))
    out = stages.run_chain(spark.range(10), {"pre": [["keep_small", {"limit": 4}]], "post": []}, "pre")
    assert out.count() == 4 and stages.run_chain(spark.range(10), {}, "pre").count() == 10
    items = spark.createDataFrame([("1", bytearray("café".encode("latin-1")), "text/html; charset=iso-8859-1")], "item_id string, body binary, content_type string")
    assert stages.run_chain(items, {"load": ["utf8"]}, "load").first().text == "café"
    with pytest.raises(ValueError):
        stages.register_stage("keep_small", lambda df: df)


def reads_and_matches(spark, data, name, *tables):
    """The query's plan reads given tables, and its rows are those of its SQL."""
    import duckdb

    df = w.queries()[name](spark, data)
    assert {f.rsplit("/", 1)[1] for f in df.inputFiles()} >= {f"{t}.parquet" for t in tables}
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{data}/{t}.parquet'")
    cur = con.execute(w.oracle_sql()[name])
    assert df.columns == [d[0] for d in cur.description]
    mine, theirs = sorted(map(str, map(tuple, df.collect()))), sorted(map(str, cur.fetchall()))
    assert mine == theirs and mine


def test_flush_levels_reads_a_table(spark, data):
    reads_and_matches(spark, data, "flush_levels", *("orders", "lineitem"))


def test_flush_levels_full_reads_a_table(spark, data):
    reads_and_matches(spark, data, "flush_levels_full", *("orders", "lineitem"))


def test_merged_mapping_reads_a_table(spark, data):
    reads_and_matches(spark, data, "merged_mapping", *("orders", "lineitem"))


def test_edited_dictionary_reads_a_table(spark, data):
    reads_and_matches(spark, data, "edited_dictionary", *("part",))


def test_audit_phases_read_their_documents_once(spark, data):
    """Native records and converted ones are each shredded by one pass, and only counts of paths are shuffled."""
    plan = studies.audit_phases(spark, data)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 2


def test_path_counts_equal_the_inventory(spark):
    rows = [("d1", "s", 0, ["a", "b"], "x"), ("d1", "s", 1, ["a", "b"], "y"), ("d1", "s", 2, ["a", "@k"], "z"), ("d2", "s", 0, ["a", "b"], " "), ("d2", "t", 1, ["a"], "x"), ("d3", "t", None, None, None)]
    nodes = spark.createDataFrame(rows, "doc_id string, source string, ord int, plain array<string>, text string")
    for options in ({}, {"attributes": False}, {"non_empty": False}):
        whole = audit.path_inventory(nodes, **options).select("source", "path", "n")
        assert sorted(map(tuple, audit.path_counts(nodes, **options).collect())) == sorted(map(tuple, whole.collect()))
