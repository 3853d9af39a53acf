"""Key detection and the key/value pairing scan over shredded nodes."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.columns import fold_key, path_edit_sim, path_prefix_sim, text_sim
from ..functions.shred import node_table
from ..session import ensure_checkpoint_dir
from . import fuzzy

#: Largest dictionary, in entries, that every short text is compared with; larger ones meet texts on segments.
COMPARED_ENTRIES = 512
#: Most distinct key texts that are broadcast.
FEW_MATCHES = 20_000
SPELLINGS = ("plain", "numbered", "attributed")
SEPARATORS = (":", "=", "→", "-")


def match_keys(nodes: DataFrame, dictionary: DataFrame, theta_key: float = 0.8, compared: int = COMPARED_ENTRIES) -> DataFrame:
    """(lang, text, key_id, sim) of the distinct texts that are keys: exact hits first, then the best fuzzy one.

    Only texts short enough for some entry take part; ties go to the smaller key id. A dictionary of at most `compared` entries is
    broadcast and compared directly; a larger one is matched by the segment join, with the same result.
    """
    entries = dictionary.filter(~F.col("is_static")).select("lang", "key_id", F.lower("surface").alias("surface")).distinct()
    n, longest = entries.agg(F.count(F.lit(1)), F.max(F.length("surface"))).first()
    texts = nodes.filter(F.col("text").isNotNull()).select("lang", "text").filter(F.length("text") <= int((longest or 0) / max(theta_key, 0.01)) + 12).distinct().withColumn("folded", fold_key("text"))
    if n <= compared:
        met = texts.join(F.broadcast(entries), "lang").filter((F.col("folded") == F.col("surface")) | fuzzy.within("folded", "surface", theta_key))
    else:
        near = fuzzy.near_pairs(texts.select("lang", F.col("folded").alias("text")).distinct(), entries.select("lang", F.col("surface").alias("text")).distinct(), theta_key)
        met = texts.join(near.select("lang", F.col("a").alias("folded"), F.col("b").alias("surface")), ["lang", "folded"]).join(entries, ["lang", "surface"])
    found = met.withColumn("sim", text_sim("folded", "surface"))
    return found.groupBy("lang", "text").agg(F.min(F.struct((-F.col("sim")).alias("d"), "key_id")).alias("best")).select("lang", "text", F.col("best.key_id").alias("key_id"), (-F.col("best.d")).alias("sim"))


def split_inline(nodes: DataFrame, dictionary: DataFrame, theta_key: float = 0.8, separators: tuple[str, ...] = SEPARATORS) -> DataFrame:
    """Expands texts of the form key, separator, value into a key node and a value node.

    The longest dictionary entry that a text begins with is its key; a text with a known separator may have a misspelt key
    before it. Ordinals become doubles of the old ones so the order stays.
    """
    entries = dictionary.filter(~F.col("is_static")).select("lang", F.lower("surface").alias("surface")).distinct()
    by_lang = entries.groupBy("lang").agg(F.collect_set("surface").alias("_surfaces"))
    text = F.col("text")
    low = F.lower(text)
    starts = F.filter("_surfaces", lambda s: F.startswith(low, s) & (F.length(low) > F.length(s)) & ~F.substring(low, F.length(s) + 1, F.lit(1)).rlike(r"[\p{L}\p{N}]"))
    longest = F.coalesce(F.array_max(F.transform(starts, lambda s: F.length(s))), F.lit(0))
    marks = "|".join("\\" + s if s in "-:=" else s for s in separators)
    before = F.regexp_extract(text, rf"^([^:=→]{{2,60}}?)\s*(?:{marks})\s*(?=\S)", 1)
    guessed = F.when((before != "") & F.exists("_surfaces", lambda s: (F.abs(F.length(s) - F.length(before)) <= 4) & (text_sim(F.lower(before), s) >= theta_key)), F.length(before)).otherwise(0)
    # where a blank is the separator, as many words as an entry has may be that entry misspelt
    words = F.split(text, " ")
    lead = lambda s: F.array_join(F.slice(words, F.lit(1), F.size(F.split(s, " "))), " ")
    spelt = F.filter("_surfaces", lambda s: (F.size(words) > F.size(F.split(s, " "))) & (F.abs(F.length(lead(s)) - F.length(s)) <= 3) & (text_sim(F.lower(lead(s)), s) >= theta_key))
    blank = F.coalesce(F.array_max(F.transform(spelt, lambda s: F.length(lead(s)))), F.lit(0))
    cut = F.when(longest > 0, longest).when(guessed > 0, guessed).otherwise(blank)
    value = F.regexp_replace(F.substring(text, F.col("_cut") + 1, F.length(text)), rf"^\s*(?:s\b)?\s*(?:{marks})?\s*", "")
    both = F.when((F.col("_cut") > 0) & (value != ""), F.array(F.struct(F.lit(0).alias("k"), F.substring(text, F.lit(1), F.col("_cut")).alias("t")), F.struct(F.lit(1).alias("k"), value.alias("t")))).otherwise(F.array(F.struct(F.lit(0).alias("k"), text.alias("t"))))
    wide = nodes.join(by_lang, "lang", "left").withColumn("_cut", F.coalesce(cut, F.lit(0))).withColumn("_part", F.explode(both))
    return wide.withColumns({"ord": F.col("ord") * 2 + F.col("_part.k"), "text": F.col("_part.t")}).select(*nodes.columns)


def split_subfields(value: Column | str, mark: str = ";") -> Column:
    """Sub-fields of one value."""
    value = F.col(value) if isinstance(value, str) else value
    return F.filter(F.transform(F.split(value, mark), lambda x: F.trim(x)), lambda x: x != "")


def similarity(kind: str, a: Column | str, b: Column | str, norm: str = "max") -> Column:
    return path_prefix_sim(a, b, norm) if kind == "prefix" else path_edit_sim(a, b)


def scan(nodes: DataFrame, matches: DataFrame, spelling: str = "numbered", sim: str = "prefix", theta_path: float = 0.5, norm: str = "max") -> DataFrame:
    """All nodes with their role (key, value, unmatched) and, for values, key and similarity.

    The last key before a node is carried along the document order by one window over doc_id; the key stays current when a
    value fails, and text before any key is unmatched.
    """
    keyed = nodes.join(matches.withColumnRenamed("sim", "key_sim"), ["lang", "text"], "left").withColumn("path", F.col(spelling))
    key = F.when(F.col("key_id").isNotNull(), F.struct("key_id", F.col("text").alias("key_text"), F.col("path").alias("key_path"), F.col("ord").alias("key_ord")))
    along = Window.partitionBy("doc_id").orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)
    carried = keyed.withColumn("last_key", F.last(key, ignorenulls=True).over(along)).withColumn("sim", similarity(sim, "path", "last_key.key_path", norm))
    role = F.when(F.col("key_id").isNotNull(), "key").when(F.col("last_key").isNotNull() & (F.col("sim") > theta_path), "value").otherwise("unmatched")
    return carried.withColumn("role", role)


def pairs_of(scanned: DataFrame) -> DataFrame:
    """(doc_id, source, key_id, key_text, value, value_no, ord, sim) of the values."""
    number = Window.partitionBy("doc_id", "last_key.key_id").orderBy("ord")
    return scanned.filter("role = 'value'").select("doc_id", "source", F.col("last_key.key_id").alias("key_id"), F.col("last_key.key_text").alias("key_text"), F.col("text").alias("value"), F.row_number().over(number).alias("value_no"), "ord", "sim")


def unmatched_of(scanned: DataFrame) -> DataFrame:
    """(doc_id, source, ord, key_ctx, text, reason) of what is neither key nor value."""
    reason = F.when(F.col("last_key").isNull(), "before any key").otherwise("too far from its key")
    return scanned.filter("role = 'unmatched'").select("doc_id", "source", "ord", F.col("last_key.key_id").alias("key_ctx"), "text", reason.alias("reason"))


def spread(matches: DataFrame, few: int = FEW_MATCHES) -> DataFrame:
    """The matches cut off, and broadcast if they are at most so many: then the nodes stay dealt by document."""
    ensure_checkpoint_dir(matches.sparkSession)
    matches = matches.checkpoint()
    return F.broadcast(matches) if matches.limit(few + 1).count() <= few else matches


def pair_values(nodes: DataFrame, dictionary: DataFrame, spelling: str = "numbered", sim: str = "prefix", theta_path: float = 0.5, theta_key: float = 0.8, impl: str = "window", norm: str = "max") -> DataFrame:
    """Key/value pairs by the carried-key scan. impl: window (default), fold (higher-order functions) or arrow (grouped Python)."""
    matches = match_keys(nodes, dictionary, theta_key)
    if impl == "window":
        return pairs_of(scan(nodes, spread(matches), spelling, sim, theta_path, norm))
    keyed = nodes.join(matches.select("lang", "text", "key_id"), ["lang", "text"], "left").select("doc_id", "source", "ord", "text", "key_id", F.col(spelling).alias("path"))
    return (fold_scan if impl == "fold" else arrow_scan)(keyed, sim, theta_path, norm)


def fold_scan(keyed: DataFrame, sim: str, theta_path: float, norm: str) -> DataFrame:
    """The scan as one fold over a document's node array; a cross-check for small documents only."""
    element = "struct<ord:int,text:string,key_id:string,path:array<string>>"
    docs = keyed.groupBy("doc_id", "source").agg(F.array_sort(F.collect_list(F.struct("ord", "text", "key_id", "path"))).alias("nodes"))
    start = F.struct(F.lit(None).cast(element).alias("k"), F.array().cast("array<struct<key_id:string,key_text:string,value:string,ord:int,sim:double>>").alias("out"))

    def step(acc: Column, n: Column) -> Column:
        s = similarity(sim, n["path"], acc["k"]["path"], norm).cast("double")
        pair = F.struct(acc["k"]["key_id"].alias("key_id"), acc["k"]["text"].alias("key_text"), n["text"].alias("value"), n["ord"].alias("ord"), s.alias("sim"))
        out = F.when(n["key_id"].isNull() & acc["k"].isNotNull() & (s > theta_path), F.concat(acc["out"], F.array(pair))).otherwise(acc["out"])
        return F.struct(F.when(n["key_id"].isNotNull(), n).otherwise(acc["k"]).alias("k"), out.alias("out"))

    flat = docs.select("doc_id", "source", F.inline(F.aggregate("nodes", start, step)["out"]))
    number = Window.partitionBy("doc_id", "key_id").orderBy("ord")
    return flat.select("doc_id", "source", "key_id", "key_text", "value", F.row_number().over(number).alias("value_no"), "ord", "sim")


def list_distance(p: list, q: list) -> int:
    row = list(range(len(q) + 1))
    for i, a in enumerate(p, 1):
        last, row[0] = row[0], i
        for j, b in enumerate(q, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (a != b))
    return row[-1]


def local_similarity(kind: str, p: list, q: list, norm: str = "max") -> float:
    """The path similarities on plain lists."""
    if kind == "edit":
        return 1.0 - list_distance(p, q) / max(len(p), len(q)) if p or q else 1.0
    if not p and not q:
        return 1.0
    common = next((i for i, (a, b) in enumerate(zip(p, q)) if a != b), min(len(p), len(q)))
    length = {"max": max(len(p), len(q)), "min": min(len(p), len(q)), "mean": (len(p) + len(q)) / 2}[norm]
    return common / length if length else 0.0


def arrow_scan(keyed: DataFrame, sim: str, theta_path: float, norm: str) -> DataFrame:
    """The scan as grouped Python, document by document."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        key, out, counts = None, [], {}
        for n in pdf.sort_values("ord").itertuples():
            if n.key_id is not None:
                key = n
            elif key is not None and (s := local_similarity(sim, list(n.path), list(key.path), norm)) > theta_path:
                counts[key.key_id] = counts.get(key.key_id, 0) + 1
                out.append((n.doc_id, n.source, key.key_id, key.text, n.text, counts[key.key_id], n.ord, s))
        return pd.DataFrame(out, columns=["doc_id", "source", "key_id", "key_text", "value", "value_no", "ord", "sim"])

    return keyed.groupBy("doc_id").applyInPandas(run, "doc_id string, source string, key_id string, key_text string, value string, value_no int, ord int, sim double")


def pair_values_hier(nodes: DataFrame, dictionary: DataFrame, theta_key: float = 0.8, theta_path: float = 0.3, spelling: str = "numbered") -> DataFrame:
    """(doc_id, source, key_path, value): leaf keys resolved under the last section key.

    One window carries two levels: the last section, and the last leaf, which is void once a newer section begins.
    A leaf that has no entry under the current section keeps its own id.
    """
    sections = dictionary.filter(F.col("parent_key_id").isNull())
    leaves = dictionary.filter(F.col("parent_key_id").isNotNull())
    top = match_keys(nodes, sections, theta_key).select("lang", "text", F.col("key_id").alias("section"))
    low = leaves.select("lang", F.lower("surface").alias("folded"), F.col("parent_key_id").alias("parent"), F.col("key_id").alias("leaf_id"), F.col("elem_name"))
    names = low.select("lang", "folded", "elem_name").distinct()
    marked = nodes.join(top, ["lang", "text"], "left").withColumn("folded", fold_key("text")).join(names, ["lang", "folded"], "left").withColumn("path", F.col(spelling))
    along = Window.partitionBy("doc_id").orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)
    section = F.last(F.when(F.col("section").isNotNull(), F.struct("ord", "section", "path")), ignorenulls=True).over(along)
    leaf = F.last(F.when(F.col("elem_name").isNotNull(), F.struct("ord", "elem_name", "path")), ignorenulls=True).over(along)
    carried = marked.withColumns({"s": section, "f": leaf}).filter(F.col("section").isNull() & F.col("elem_name").isNull() & F.col("s").isNotNull())
    live = F.col("f").isNotNull() & (F.col("f.ord") > F.col("s.ord"))
    near = F.when(live, path_prefix_sim("path", "f.path")).otherwise(path_prefix_sim("path", "s.path"))
    named = carried.filter(near > theta_path).withColumns({"parent": F.col("s.section"), "leaf": F.when(live, F.col("f.elem_name"))})
    resolved = named.join(low.select("parent", F.col("elem_name").alias("leaf"), "leaf_id", "lang"), ["lang", "parent", "leaf"], "left")
    key_path = F.when(F.col("leaf").isNull(), F.col("parent")).otherwise(F.coalesce("leaf_id", F.concat_ws("/", "parent", "leaf")))
    return resolved.select("doc_id", "source", key_path.alias("key_path"), F.col("text").alias("value"), "ord")


def reroot(nodes: DataFrame, tag: str) -> DataFrame:
    """Only what lies below the first element of that name; paths start there. Documents without it keep all their nodes."""
    inside = F.array_position("plain", tag)
    has = F.max(F.when(inside > 0, 1).otherwise(0)).over(Window.partitionBy("doc_id"))
    tail = lambda c: F.when(inside > 0, F.slice(c, inside.cast("int"), F.size(c))).otherwise(F.col(c))
    return nodes.withColumn("_has", has).filter((F.col("_has") == 0) | (inside > 0)).drop("_has").withColumns({c: tail(c) for c in SPELLINGS if c in nodes.columns})


def inject_keyless(nodes: DataFrame, rules: dict[str, str]) -> DataFrame:
    """Gives keyless elements (last step -> key text) a synthetic key node just before them."""
    name = F.element_at("plain", -1)
    table = F.create_map(*[F.lit(x) for kv in rules.items() for x in kv])
    key = F.try_element_at(table, name)
    fake = F.struct((F.col("ord") * 2).alias("ord"), key.alias("text"))
    true = F.struct((F.col("ord") * 2 + 1).alias("ord"), F.col("text").alias("text"))
    both = F.when(key.isNotNull(), F.array(fake, true)).otherwise(F.array(true))
    return nodes.withColumn("_n", F.explode(both)).withColumns({"ord": F.col("_n.ord"), "text": F.col("_n.text")}).drop("_n")


def emit_xml(pairs: DataFrame, dictionary: DataFrame, root: str = "document", keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, the keep columns, xml): pairs as elements in document order; repeated keys stand in a container named after them.

    Columns to keep have one value in a document. Pairs that are dealt by document stay so.
    """
    names = dictionary.groupBy("key_id").agg(F.min("elem_name").alias("elem"))
    esc = lambda c: F.replace(F.replace(F.replace(c, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))
    named = pairs.join(F.broadcast(names), "key_id").withColumn("e", F.concat(F.lit("<"), F.col("elem"), F.lit(">"), esc(F.col("value")), F.lit("</"), F.col("elem"), F.lit(">")))
    per_key = named.groupBy("doc_id", *keep, "elem").agg(F.array_sort(F.collect_list(F.struct("ord", "e"))).alias("es"))
    body = F.array_join(F.transform("es", lambda x: x["e"]), "")
    block = F.when(F.size("es") > 1, F.concat(F.lit("<list_of_"), F.col("elem"), F.lit(">"), body, F.lit("</list_of_"), F.col("elem"), F.lit(">"))).otherwise(body)
    docs = per_key.select("doc_id", *keep, F.struct(F.element_at("es", 1)["ord"].alias("ord"), block.alias("b")).alias("p")).groupBy("doc_id", *keep).agg(F.array_sort(F.collect_list("p")).alias("ps"))
    return docs.select("doc_id", *keep, F.concat(F.lit(f"<{root}>"), F.array_join(F.transform("ps", lambda p: p["b"]), ""), F.lit(f"</{root}>")).alias("xml"))


def html_pairs(notices: DataFrame, dictionary: DataFrame, inline: bool = False, simplify: bool = False, **options) -> DataFrame:
    """Notices to pairs: shred, re-root to the main element, optionally expand inline keys, scan."""
    spelling = options.get("spelling", "numbered")
    return pair_values(prepared_nodes(notices, dictionary, inline, simplify, (spelling,)), dictionary, **options)


def prepared_nodes(notices: DataFrame, dictionary: DataFrame, inline: bool = False, simplify: bool = False, spellings: tuple[str, ...] = SPELLINGS) -> DataFrame:
    """Notices shredded with the wanted path spellings (plain ones are always there), re-rooted to the main element."""
    fields = ("ord", *dict.fromkeys(("plain", *spellings)), "text")
    nodes = node_table(notices, "body", ("doc_id", "source", "lang"), "html", simplify=simplify, fields=fields)
    nodes = reroot(nodes.filter("ord is not null"), "main")
    return split_inline(nodes, dictionary) if inline else nodes
