"""Further registered workloads: the expert's loops, mapping and dictionary work, alternatives side by side."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions.columns import path_text
from .functions.shred import node_table
from .operators import archive, audit, measures, pairing, stages
from .operators import dictionary as dicts
from .plans import baselines, loader, mapping
from .sources import notices as src
from .workloads import _COUNTS, _HEAD, _LINES, _LOT, _ROWS, _XML, _XML_LOTS, BASE, FIELDS, INVENTORY, MAPPING, PARTIAL, SMALL, SQL, TARGET, _words, entities, inventory, query, rows_to_insert, table, truth, xml_nodes

# dictionary and mapping work

#: Frequent lines that an expert calls values, not keys, for the static filter: every candidate of more than 40 letters.
_CANDIDATES = f"SELECT lang, t AS text, count(*) AS n_docs FROM ({_LINES}) WHERE length(t) BETWEEN 3 AND 60 GROUP BY lang, t HAVING count(*) >= 3"


@query(f"SELECT * FROM ({_CANDIDATES}) WHERE length(text) <= 40")
def candidates_without_static(spark, sf):
    found = dicts._cut(dicts.key_candidates(dicts.lines_of(table(spark, sf, "documents")), 3))
    return dicts.drop_static(found, found.filter(F.length("text") > 40).select("lang", "text"))


@query("SELECT 'en' AS lang, p_name AS surface, trim(regexp_replace(lower(p_name), '[^a-z0-9]+', '_', 'g'), '_') AS elem_name FROM (SELECT DISTINCT p_name FROM part)")
def assembled_dictionary(spark, sf):
    """A dictionary made of part names that are their own groups."""
    names = table(spark, sf, "part").groupBy(F.col("p_name").alias("text")).agg(F.count(F.lit(1)).alias("n_docs")).withColumn("lang", F.lit("en"))
    alone = dicts.build_synsets(names, dicts.similar_pairs(names, 0.999))
    return dicts.make_dictionary(alone).select("lang", "surface", "elem_name")


def _rows(rows: list[tuple]) -> str:
    return ", ".join("(" + ", ".join("NULL" if x is None else f"'{x}'" for x in r) + ")" for r in rows)


_BRANDS = "SELECT DISTINCT p_brand AS b, p_name AS t FROM part"


@query(f"""SELECT DISTINCT 'en' AS lang, CASE b WHEN 'Brand#12' THEN 'Brand#11' ELSE b END AS key_id, t AS surface, CASE b WHEN 'Brand#12' THEN 'Brand#11' WHEN 'Brand#13' THEN 'renamed' ELSE b END AS elem_name FROM ({_BRANDS}) WHERE NOT (b = 'Brand#14' AND length(t) % 2 = 0)
UNION SELECT 'en', b, upper(t), CASE b WHEN 'Brand#13' THEN 'renamed' ELSE b END FROM ({_BRANDS}) WHERE b IN ('Brand#11', 'Brand#13')""")
def edited_dictionary(spark, sf):
    """Every edit of an expert on the dictionary of the brands' part names: add and remove surfaces, merge a key into another, rename an element."""
    names = table(spark, sf, "part").select(F.lit("en").alias("lang"), F.col("p_brand").alias("key_id"), F.col("p_name").alias("surface")).distinct()
    d = names.withColumns({"parent_key_id": F.lit(None).cast("string"), "elem_name": F.col("key_id"), "is_static": F.lit(False), "version": F.lit("1")})
    edit = lambda op, rows, surface: rows.select(F.lit(op).alias("op"), "lang", "key_id", surface.alias("surface"), F.lit(None).cast("string").alias("target"))
    edits = spark.createDataFrame([("merge", "en", "Brand#12", None, "Brand#11"), ("rename", None, "Brand#13", None, "renamed")], "op string, lang string, key_id string, surface string, target string")
    edits = edits.unionByName(edit("add", names.filter(F.col("key_id").isin("Brand#11", "Brand#13")), F.upper("surface")))
    edits = edits.unionByName(edit("remove", names.filter((F.col("key_id") == "Brand#14") & (F.length("surface") % 2 == 0)), F.col("surface")))
    return dicts.edit_dictionary(d, edits).select("lang", "key_id", "surface", "elem_name").distinct()


_PATTERN_SPEC = json.dumps({"version": 1, "map": [
    {"entity": "contract", "path": "/notice", "fields": {"reference": "//reference", "priority": "/notice/*/priority"}, "recodes": {"priority": {"1-URGENT": "first", "5-LOW": "last"}}, "children": [{"entity": "lot", "path": "lots/lot", "fields": {"item": "~it.m"}}]}]})


@query(BASE + " SELECT CAST(o_orderkey AS VARCHAR) AS reference, CASE o_orderpriority WHEN '1-URGENT' THEN 'first' WHEN '5-LOW' THEN 'last' ELSE o_orderpriority END AS priority" + _XML)
def mapped_by_patterns(spark, sf):
    """The path dialect's //, * and ~ steps, with recoded values."""
    target = mapping.load_target(json.dumps({"entities": [{"name": "contract", "fields": {"reference": "text", "priority": "text"}}, {"name": "lot", "fields": {"item": "text"}, "links": {"contract_id": "contract"}}]}))
    return loader.extract_entities(xml_nodes(spark, sf), mapping.load_mapping(_PATTERN_SPEC), target, ("contract",))["contract"].select("reference", "priority")


_OTHER = json.dumps({"version": 3, "map": [{"entity": "contract", "path": "/notice", "fields": {"priority": "head/urgency", "total": "head/total"}, "recodes": {"priority": {"x": "y"}}, "children": [{"entity": "lot", "path": "lots/lot", "fields": {"item": "item", "brand": "brand"}}, {"entity": "buyer", "fields": {"name": "head/buyer"}}]}]})


@query(INVENTORY + f" SELECT entity, field, path, CAST(coalesce(sum(n), 0) AS BIGINT) AS n FROM (VALUES {_rows([('contract', 'reference', '/notice/head/reference'), ('contract', 'priority', '/notice/head/priority'), ('contract', 'priority', '/notice/head/urgency'), ('contract', 'total', '/notice/head/total'), ('lot', 'item', '/notice/lots/lot/title'), ('lot', 'item', '/notice/lots/lot/item'), ('lot', 'brand', '/notice/lots/lot/brand'), ('buyer', 'name', '/notice/head/buyer')])}) m(entity, field, path) LEFT JOIN v USING (path) GROUP BY entity, field, path")
def merged_mapping(spark, sf):
    """Two experts' mappings in one: all paths of both, entities matched by name and place, with the nodes of the XML notices that each path takes."""
    named = mapping.mapped_paths(spark, mapping.merge_mappings(mapping.load_mapping(SMALL), mapping.load_mapping(_OTHER)))
    seen = inventory(spark, sf).select(F.col("path").alias("seen"), "n")
    hits = seen.join(F.broadcast(named), F.expr("seen rlike pattern")).groupBy("entity", "field", "path").agg(F.sum("n").alias("n"))
    return named.join(hits, ["entity", "field", "path"], "left").select("entity", "field", "path", F.coalesce("n", F.lit(0)).alias("n"))


_CALLS = "kind = " + _words(src.CALL, src.CALL, "true")


@query(BASE + f" SELECT CAST(o_orderkey AS VARCHAR) AS doc_id, CASE WHEN o_orderstatus = 'F' THEN 'award' ELSE 'call' END AS record_kind" + _XML)
def record_kinds(spark, sf):
    """Calls and awards told apart by the words of four languages."""
    return mapping.record_kind(xml_nodes(spark, sf), "/notice/head/kind", {"call": src.CALL, "award": src.AWARD})


_BRANCHES = {
    "call": json.dumps({"version": 1, "map": [{"entity": "call", "path": "/notice", "fields": {"reference": "head/reference"}}]}),
    "award": json.dumps({"version": 1, "map": [{"entity": "award", "path": "/notice", "fields": {"reference": "head/reference"}, "children": [{"entity": "winner", "path": "lots/lot", "fields": {"name": "winner"}}]}]}),
}


@query(BASE + " SELECT entity, reference, name, count(*) AS n FROM (SELECT CASE WHEN o_orderstatus = 'F' THEN 'award' ELSE 'call' END AS entity, CAST(o_orderkey AS VARCHAR) AS reference, NULL AS name" + _XML + " UNION ALL SELECT 'winner', NULL, s_name" + _XML_LOTS + " AND o_orderstatus = 'F') GROUP BY ALL")
def kind_branches(spark, sf):
    """Each kind of record is mapped by its own branch: awards have winners, calls have none."""
    target = mapping.load_target(json.dumps({"entities": [{"name": "call", "fields": {"reference": "text"}}, {"name": "award", "fields": {"reference": "text"}}, {"name": "winner", "fields": {"name": "text"}, "links": {"award_id": "award"}}]}))
    nodes = xml_nodes(spark, sf)
    kinds = mapping.record_kind(nodes, "/notice/head/kind", {"call": src.CALL, "award": src.AWARD})
    e = loader.extract_by_kind(nodes, kinds, {k: mapping.load_mapping(v) for k, v in _BRANCHES.items()}, target)
    none = F.lit(None).cast("string")
    heads = [e[k].select(F.lit(k).alias("entity"), "reference", none.alias("name")) for k in ("call", "award")]
    rows = heads[0].unionByName(heads[1]).unionByName(e["winner"].select(F.lit("winner").alias("entity"), none.alias("reference"), "name"))
    return rows.groupBy("entity", "reference", "name").agg(F.count(F.lit(1)).alias("n"))


@query(BASE + f" SELECT CAST(o_orderkey AS VARCHAR) AS doc_id, CAST(row_number() OVER (PARTITION BY o_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS INTEGER) AS occurrence, p_name AS value" + _XML_LOTS)
def item_occurrences(spark, sf):
    return loader.occurrences(xml_nodes(spark, sf), "/notice/lots/lot/item").select("doc_id", "occurrence", "value")


@query(BASE + f" SELECT CAST(o_orderkey AS VARCHAR) AS doc_id, p_name AS value FROM (SELECT *, row_number() OVER (PARTITION BY o_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate) AS k {_XML_LOTS}) WHERE k = 2")
def second_items(spark, sf):
    return loader.occurrences(xml_nodes(spark, sf), "/notice/lots/lot/item[2]").select("doc_id", "value")


@query(BASE + " SELECT o_orderkey, c_name, CASE WHEN c_nationkey_hidden IS NULL THEN NULL ELSE c_name END AS linked FROM (SELECT o_orderkey, c_name, CASE WHEN nation < 3 THEN nation END AS c_nationkey_hidden" + _XML + ")")
def deferred_pointers(spark, sf):
    """Orders point to buyers by name after both exist; buyers of other sources are unknown and leave the pointer null."""
    cust = table(spark, sf, "customer").filter("c_nationkey between 0 and 5")
    orders = table(spark, sf, "orders").join(cust, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_name", F.lit(None).cast("long").alias("buyer_id"))
    buyers = cust.filter("c_nationkey < 3").select("c_name", F.xxhash64("c_name").alias("id"))
    out = loader.two_phase(orders, buyers, ["c_name"], "buyer_id")
    return out.select("o_orderkey", "c_name", F.when(F.col("buyer_id") == F.xxhash64("c_name"), F.col("c_name")).alias("linked"))


@query("SELECT 'content' AS variant, CAST(0 AS BIGINT) AS repeated UNION ALL SELECT 'ordinal', 0 UNION ALL SELECT 'by day', (SELECT count(*) FROM (SELECT o_orderdate FROM orders GROUP BY 1 HAVING count(*) > 1))")
def id_variants(spark, sf):
    """Ids that occur more than once: hashed keys and task ordinals never repeat, a natural key that is none does."""
    o = table(spark, sf, "orders")
    variants = {"content": o.select(F.xxhash64("o_orderkey").alias("id")), "ordinal": loader.monotonic_ids(o), "by day": o.select(F.col("o_orderdate").alias("id"))}
    parts = [loader.check_unique(df).agg(F.count(F.lit(1)).alias("repeated")).select(F.lit(k).alias("variant"), "repeated") for k, df in variants.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query(BASE + " SELECT field, count(*) AS bad, any_value(n) AS total FROM (SELECT unnest(['priority', 'urgent']) AS field, (SELECT count(*) FROM s WHERE nation BETWEEN 0 AND 5) AS n" + _XML + ") GROUP BY field")
def type_mismatches(spark, sf):
    """Fields whose values don't fit a target type: priorities are no numbers, yes and no are no dates; references are integers."""
    e = {"contract": entities(spark, sf, "contract")["contract"]}
    wrong = mapping.load_target(json.dumps({"entities": [{"name": "contract", "fields": {"reference": "integer", "priority": "number", "urgent": "date"}}]}))
    return loader.type_mismatches(e, wrong).select("field", "bad", "total")


# the loops


def _mass(k: int) -> str:
    return "sum(n) FILTER (WHERE " + " OR ".join([f"path IN {p}" for p in _STEPS[: k + 1]]) + ")"


_STEPS = ["('/notice/head/reference', '/notice/head/priority', '/notice/lots/lot/item')", "('/notice/lots/lot/brand', '/notice/lots/lot/quantity', '/notice/lots/lot/price')", "('/notice/head/buyer', '/notice/head/total')"]
_ROUND = " UNION ALL ".join(f"SELECT CAST({k} AS INTEGER) AS round, round({_mass(k)} / sum(n), 9) AS mapped_mass FROM v" for k in range(3))


@query(INVENTORY + " " + _ROUND)
def amend_history(spark, sf):
    """The reviewer adds paths round by round; the share of the mapped mass rises with each."""
    inv = dicts._cut(inventory(spark, sf).select("source", "path", "n"))
    additions = iter([("brand", "quantity", "price"), ("buyer", "total")])
    mapped = mapping.mapped_paths(spark, mapping.load_mapping(SMALL))
    history = []

    def look(patterns: DataFrame) -> None:
        c = audit.coverage(inv, patterns).agg((F.sum("mapped_mass") / (F.sum("mapped_mass") + F.sum("unmapped_mass")))).first()[0]
        history.append((len(history), round(float(c), 9)))

    look(mapped)

    def reviewer(queue: DataFrame):
        names = next(additions, ())
        add = spark.createDataFrame([(f"^/notice/(?:head|lots/lot)/{n}$",) for n in names], "pattern string")
        seen.append(add)
        return add, spark.createDataFrame([], "path string")

    seen: list[DataFrame] = []
    audit.amend(inv, mapped, reviewer, rounds=2)
    for add in seen:
        mapped = mapped.select("pattern").unionByName(add)
        look(mapped)
    return spark.createDataFrame(history, "round int, mapped_mass double")


@query(BASE + " SELECT * FROM (SELECT CAST(0 AS INTEGER) AS round, 0.0 AS lots_with_items UNION ALL SELECT 1, 1.0) WHERE (SELECT count(*) FROM l WHERE nation BETWEEN 0 AND 5) > 0 UNION ALL SELECT 0, 1.0 WHERE (SELECT count(*) FROM l WHERE nation BETWEEN 0 AND 5) = 0")
def expert_cycle(spark, sf):
    """Map, load, validate, remap: the first mapping looks for items where there are none; the second loads them all."""
    nodes = dicts._cut(xml_nodes(spark, sf))
    target = mapping.load_target(json.dumps({"entities": [{"name": "lot", "fields": {"no": "text", "item": "text"}}]}))
    spec = lambda path: mapping.load_mapping(json.dumps({"version": 1, "map": [{"entity": "lot", "path": "/notice/lots/lot", "fields": {"no": "@no", "item": path}}]}))

    def judge(e, m):
        rate = e["lot"].agg(F.coalesce(F.count("item") / F.nullif(F.count(F.lit(1)), F.lit(0)), F.lit(1.0))).first()[0]
        return float(rate), spec("item")

    _, history = loader.expert_cycle(lambda m: loader.extract_entities(nodes, m, target, ("lot",)), judge, spec("title"))
    return spark.createDataFrame(history, "round int, lots_with_items double")


# coverage in two phases, review orders


_PHASES = FIELDS + """, d AS (SELECT source, nation, o_orderkey, key_id, count(v) AS n FROM f WHERE v IS NOT NULL AND (nation BETWEEN 0 AND 5 OR nation BETWEEN 13 AND 16) GROUP BY ALL)
SELECT source, CASE WHEN nation < 6 THEN 'native' ELSE 'converted' END AS phase, count(DISTINCT CASE WHEN nation < 6 THEN key_id ELSE concat(key_id, n > 1) END) AS paths, CAST(sum(n) AS BIGINT) AS mass FROM d GROUP BY source, nation"""


@query(_PHASES)
def audit_phases(spark, sf):
    """Sources audited one by one: native XML by its own paths first, then HTML by the paths of its converted XML (a key that repeats in a
    document has a second path, in its list)."""
    records = node_table(src.notices(spark, sf, layouts=("xml",)), "body", ("source",), "xml", fields=("ord", "plain", "text"))
    native = audit.path_counts(records, attributes=False).filter("path like '/notice/head/%' or path like '/notice/lots/lot/%'")
    d = src.dictionary(spark)
    nodes = pairing.prepared_nodes(src.notices(spark, sf, layouts=("table",)), d, spellings=("numbered",))
    pairs = pairing.pair_values(dicts._cut(nodes.select("doc_id", "source", "lang", "ord", "numbered", "text")), d)
    converted = audit.path_counts(emitted_nodes(pairs, d))
    return audit.audit_phases({"native": native, "converted": converted})


def emitted_nodes(pairs: DataFrame, d: DataFrame) -> DataFrame:
    """Pairs written as XML and shredded again."""
    xml = pairing.emit_xml(pairs, d, keep=("source",)).withColumn("lang", F.lit(""))
    return node_table(xml, "xml", ("doc_id", "source", "lang"), "xml", fields=("ord", "tag", "plain", "text"))


_TOP_ROUNDS = INVENTORY + """, t AS (SELECT path, CAST(sum(n) AS BIGINT) AS n FROM v GROUP BY path), r AS (SELECT path, n, row_number() OVER (ORDER BY n DESC, path) AS f, row_number() OVER (ORDER BY n ASC, path) AS b FROM t)
SELECT 'frequency' AS method, CAST(ceil(min(k) / 3.0) AS INTEGER) AS rounds FROM (SELECT f AS k, sum(n) OVER (ORDER BY f) / sum(n) OVER () AS share FROM r) WHERE share >= 0.9
UNION ALL SELECT 'tail', CAST(ceil(min(k) / 3.0) AS INTEGER) FROM (SELECT b AS k, sum(n) OVER (ORDER BY b) / sum(n) OVER () AS share FROM r) WHERE share >= 0.9"""


@query(_TOP_ROUNDS)
def rounds_to_coverage(spark, sf):
    """Rounds of three reviewed paths each until 90 % of the mass is seen, most frequent first against rarest first."""
    return _review_rounds(spark, sf, ("frequency", "tail"))


@query()
def rounds_to_coverage_random(spark, sf):
    """The same for random and weighted queues, whose hash orders SQL does not share; tests hold them against the two above."""
    return _review_rounds(spark, sf, ("random", "weighted"))


def _review_rounds(spark, sf, orders) -> DataFrame:
    inv = dicts._cut(inventory(spark, sf).groupBy("path").agg(F.sum("n").alias("n")).withColumn("source", F.lit("")))
    return spark.createDataFrame([(k, audit.rounds_to_coverage(inv, k, 3, 0.9)) for k in orders], "method string, rounds int")


# alternatives side by side


@query(FIELDS + ", t AS (SELECT count(v) AS n FROM f WHERE nation = 23 AND key_id IN ('buyer', 'item') AND v IS NOT NULL) SELECT 'hierarchical' AS dictionary, n AS hits, n AS found, n AS \"true\" FROM t UNION ALL SELECT 'flat', 0, n, n FROM t")
def flat_against_hierarchical(spark, sf):
    """One leaf label under two sections: flat keys can't say whose name a value is, key paths can."""
    d = src.name_dictionary(spark)
    docs = src.notices(spark, sf, layouts=("hierarchy",))
    nodes = dicts._cut(pairing.prepared_nodes(docs, src.dictionary(spark)))
    true = truth(spark, sf, ("hierarchy",)).filter(F.col("key_id").isin("buyer", "item")).withColumn("key_id", F.concat("key_id", F.lit("/name")))
    hier = pairing.pair_values_hier(nodes, d).filter(F.col("key_path").contains("/name")).select("doc_id", F.col("key_path").alias("key_id"), "value")
    leaf = d.filter("parent_key_id is not null").withColumns({"key_id": F.lit("name"), "parent_key_id": F.lit(None).cast("string")}).distinct()
    flat = pairing.pair_values(nodes, d.filter("parent_key_id is null").union(leaf)).filter("key_id = 'name'").select("doc_id", "key_id", "value")
    parts = [measures.score_pairs(x, true).select(F.lit(k).alias("dictionary"), "hits", "found", "true") for k, x in (("hierarchical", hier), ("flat", flat))]
    return parts[0].unionByName(parts[1])


@query(FIELDS + ", t AS (SELECT nation, count(v) AS n FROM f WHERE nation BETWEEN 17 AND 20 AND v IS NOT NULL GROUP BY nation) SELECT source, n AS any_separator, CASE WHEN nation = 17 THEN n ELSE 0 END AS colon_only FROM t JOIN (SELECT DISTINCT source, nation FROM s) USING (nation)")
def separators_against_none(spark, sf):
    """Flat lines: a split at the colon finds the pairs of one source; matching the key's own text finds all of them."""
    docs = src.notices(spark, sf, layouts=("flat",))
    true = truth(spark, sf, ("flat",)).join(docs.select("doc_id", "source"), "doc_id")
    d = src.dictionary(spark)
    any_ = pairing.html_pairs(docs, d, inline=True)
    colon = baselines.split_at_separator(node_table(docs, "body", ("doc_id", "source", "lang"), fields=("ord", "plain", "text")), ":", d)
    hits = lambda found, name: _hits_by_source(found, true).withColumnRenamed("hits", name)
    return hits(any_, "any_separator").join(hits(colon, "colon_only"), "source", "full_outer").select("source", F.coalesce("any_separator", F.lit(0)).alias("any_separator"), F.coalesce("colon_only", F.lit(0)).alias("colon_only"))


def _hits_by_source(found: DataFrame, true: DataFrame) -> DataFrame:
    a = found.groupBy("doc_id", "key_id", "value").agg(F.count(F.lit(1)).alias("f"))
    b = true.groupBy("source", "doc_id", "key_id", "value").agg(F.count(F.lit(1)).alias("t"))
    return b.join(a, ["doc_id", "key_id", "value"]).groupBy("source").agg(F.sum(F.least("f", "t")).alias("hits"))


@query("""WITH i AS (SELECT DISTINCT lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)', 1)) AS source, CAST(unnest(regexp_extract_all(url, '/(\\d+)(?:[/?#]|$)', 1)) AS BIGINT) AS item_id FROM pages)
SELECT source, max(item_id) - min(item_id) + 1 AS brute_force, count(*) AS harvested, count(*) / (max(item_id) - min(item_id) + 1) AS hit_rate FROM i GROUP BY source""")
def brute_force_crawl(spark, sf):
    """Requests of trying every id between a source's first and last, against fetching the ids found in links."""
    return archive.brute_force_cost(archive.harvest_ids(table(spark, sf, "pages")))


@query("SELECT 'row by row' AS method, count(*) AS \"rows\", count(*) AS batches FROM orders UNION ALL SELECT 'pooled', count(*), CAST(ceil(count(*) / 500.0) AS BIGINT) FROM orders")
def insert_batches(spark, sf):
    """Statements of inserting row by row against pools of 500 rows, dealt by reserved id blocks."""
    o = table(spark, sf, "orders").select("o_orderkey")
    return loader.insert_cost(o, 1, "row by row").unionByName(loader.insert_cost(o, 500, "pooled"))


@query(BASE + " SELECT 'parsed once' AS method, count(*) AS parsed FROM s WHERE nation BETWEEN 0 AND 5 UNION ALL SELECT 'parsed for each field', 2 * count(*) FROM s WHERE nation BETWEEN 0 AND 5")
def parses_counted(spark, sf):
    """Documents that went through the parser, counted where it runs."""
    docs = src.notices(spark, sf, layouts=("xml",))
    paths = {"reference": "/notice/head/reference", "priority": "/notice/head/priority"}
    return measures.count_parses(docs, paths)


# sizes and rankings


_LOGICAL = _COUNTS + """, x2 AS (SELECT source, length(CAST(o_orderkey AS VARCHAR)) + length(o_orderpriority) AS b FROM s WHERE nation BETWEEN 0 AND 5), e AS (SELECT source, count(*) AS entries, CAST(sum(b) AS BIGINT) AS bytes FROM x2 GROUP BY source)"""


@query(_LOGICAL + " SELECT source, bytes, entries, bytes / entries AS bytes_per_entry FROM e")
def text_bytes_per_entry(spark, sf):
    """Bytes of the contracts' reference and priority texts, in all and by publication."""
    e = entities(spark, sf, "contract", "publication")
    sizes = measures.text_sizes({"contract": e["contract"].select("source", "reference", "priority")})
    return measures.bytes_per_entry(sizes, measures.entry_counts(e["publication"])).select("source", "bytes", "entries", "bytes_per_entry")


def _top(metric: str) -> str:
    return _LOGICAL + f" SELECT source, {metric} AS metric, rank FROM (SELECT source, {metric}, CAST(rank() OVER (ORDER BY {metric} DESC) AS INTEGER) AS rank FROM (SELECT *, bytes / entries AS bytes_per_entry FROM e)) WHERE rank <= 5"


@query(_top("bytes"))
def top_sources_by_size(spark, sf):
    return measures.top_k(text_bytes_per_entry(spark, sf), "bytes", 5).select("source", F.col("bytes").alias("metric"), "rank")


@query(_top("bytes_per_entry"))
def top_sources_by_bytes_per_entry(spark, sf):
    return measures.top_k(text_bytes_per_entry(spark, sf), "bytes_per_entry", 5).select("source", F.col("bytes_per_entry").alias("metric"), "rank")


# stage chains


_CHAINED = "SELECT source, path, CAST(sum(n) AS BIGINT) AS n FROM (" + " UNION ALL ".join(f"SELECT source, '/notice/lots/lot/{k}' AS path, count({e}) AS n FROM l WHERE nation IN (6, 7) GROUP BY source" for k, e in _LOT.items()) + ") WHERE n > 0 GROUP BY ALL"


@query(BASE + " " + _CHAINED)
def stage_chains(spark, sf):
    """Two sources with chains of their own: numbered siblings folded in one, numbered hierarchies nested in the other."""
    chains = {"xml_numbered": {"post": ["fold_numbered"]}, "xml_nested": {"post": [["nest_numbered", {"pattern": r"^(.*?)_(\d+)_(.+)$"}]]}}
    parts = [stages.run_chain(xml_nodes(spark, sf, layout), chain, "post") for layout, chain in chains.items()]
    out = parts[0].unionByName(parts[1]).filter(F.element_at("plain", 2) == "lots")
    return out.groupBy("source", path_text("plain").alias("path")).agg(F.count(F.lit(1)).alias("n"))


# the whole target schema's order of insertion

#: The 33 tables of the published schema and the tables their 59 foreign keys point to.
FULL_SCHEMA = {
    "publication": "contract",
    "contract": "price price price address buyer buyer body body body address",
    "court_proceedings_contract": "contract", "court_interventions_contract": "contract", "additional_objects_contract": "contract",
    "funding_contract": "contract price", "contract_award_criteria": "contract", "other_publications_contract": "contract publication",
    "address": "", "price": "", "lot_award_criteria": "lot", "body": "address",
    "lot": "contract price price address winning_bid", "funding_lot": "lot price", "lot_additional_objects": "lot",
    "winning_bid": "price price bidder", "appendices_agreement": "winning_bid document", "amendments_agreement": "winning_bid document",
    "assigned_announcement_ids": "contract", "assigned_contract_ids": "contract", "bidder": "body", "subcontractors_bidder": "bidder body",
    "additional_objects_bidder": "bidder document", "bid": "lot price bidder", "bid_documents": "bid document", "buyer": "body",
    "document": "contract", "other_versions_document": "document document", "winning_bid_payments": "winning_bid price",
    "related_announcement_ids": "contract", "subcontractors_bodies": "bidder body", "subcontractors_documents": "bidder document", "corrigenda": "",
}
_EDGES = ", ".join(f"('{a}', '{b}')" for a, to in FULL_SCHEMA.items() for b in to.split())


@query(_COUNTS.replace("WITH ", "WITH RECURSIVE ", 1) + f""", e(a, b) AS (VALUES {_EDGES}), z AS (SELECT unnest({list(FULL_SCHEMA)}) AS entity),
w(entity, level) AS (SELECT entity, 0 FROM z WHERE entity NOT IN (SELECT a FROM e) UNION SELECT e.a, level + 1 FROM w JOIN e ON e.b = w.entity)
SELECT z.entity, CAST(max(level) AS INTEGER) AS level, (SELECT count(*) FROM e WHERE e.a = z.entity) AS keys, coalesce(any_value(rows), 0) AS rows FROM z JOIN w USING (entity) LEFT JOIN {_ROWS} r ON r.entity = z.entity GROUP BY z.entity""")
def flush_levels_full(spark, sf):
    """Insertion order of the published 33-table schema, with the rows that the notices put into each table: a table's level is its longest chain of keys."""
    levels = loader.flush_order({k: set(v.split()) for k, v in FULL_SCHEMA.items()})
    order = spark.createDataFrame([(n, k, len(FULL_SCHEMA[n].split())) for k, level in enumerate(levels) for n in level], "entity string, level int, keys long")
    return order.join(rows_to_insert(spark, sf), "entity", "left").select("entity", "level", "keys", F.coalesce("rows", F.lit(0)).alias("rows"))
