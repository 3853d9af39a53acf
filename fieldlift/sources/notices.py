"""Notices rendered from the star tables: lazy plans, so the base tables stay the ground truth.

One notice per order. The buyer's nation is the source and picks format and layout: 0-5 regular XML, 6 XML with numbered
siblings, 7 XML with numbered hierarchies, 8 CSV, 9-12 HTML sections, 13-16 HTML tables, 17-20 flat HTML lines, 21-22
mixed HTML, 23 HTML with repeated leaf names, 24 HTML with form widgets. Rendering uses column functions only.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Labels of the keys by language, in the order en, fr, de, es.
LANGS = ("en", "fr", "de", "es")
LABELS = {
    "reference": ("Reference number", "Numéro de référence", "Aktenzeichen", "Número de referencia"),
    "kind": ("Type of notice", "Type de marché", "Art der Bekanntmachung", "Tipo de anuncio"),
    "published": ("Publication date", "Date de parution", "Tag der Veröffentlichung", "Fecha de publicación"),
    "total": ("Total value", "Valeur totale", "Gesamtwert", "Valor total"),
    "priority": ("Priority", "Priorité", "Dringlichkeit", "Prioridad"),
    "urgent": ("Accelerated procedure", "Procédure accélérée", "Beschleunigtes Verfahren", "Procedimiento acelerado"),
    "buyer": ("Contracting authority", "Pouvoir adjudicateur", "Auftraggeber", "Poder adjudicador"),
    "segment": ("Main activity", "Activité principale", "Haupttätigkeit", "Actividad principal"),
    "country": ("Country", "Pays", "Staat", "País"),
    "region": ("Region of delivery", "Région de livraison", "Lieferregion", "Región de entrega"),
    "item": ("Item description", "Description du lot", "Beschreibung des Loses", "Descripción del lote"),
    "brand": ("Brand name", "Marque", "Markenname", "Marca comercial"),
    "quantity": ("Quantity", "Quantité", "Menge", "Cantidad"),
    "price": ("Price offered", "Prix offert", "Angebotspreis", "Precio ofertado"),
    "shipped": ("Delivery on", "Livraison le", "Lieferung am", "Entrega el"),
    "winner": ("Name of contractor", "Nom du titulaire", "Name des Auftragnehmers", "Nombre del contratista"),
}
YES, NO = ("yes", "oui", "ja", "sí"), ("no", "non", "nein", "no")
CALL, AWARD = ("call", "appel", "Ausschreibung", "licitación"), ("award", "attribution", "Vergabe", "adjudicación")
HEAD = ("reference", "kind", "published", "total", "priority", "urgent", "buyer", "segment", "country", "region")
LOT = ("item", "brand", "quantity", "price", "shipped", "winner")
#: Separators of the flat layout for the nations 17 to 20.
SEPARATORS = (" : ", " = ", " ", " → ")
LAYOUTS = {**{k: "xml" for k in range(6)}, 6: "xml_numbered", 7: "xml_nested", 8: "csv", **{k: "sections" for k in range(9, 13)}, **{k: "table" for k in range(13, 17)}, **{k: "flat" for k in range(17, 21)}, 21: "mixed", 22: "mixed", 23: "hierarchy", 24: "widgets"}
FORMATS = {k: "xml" if v.startswith("xml") else "csv" if v == "csv" else "html" for k, v in LAYOUTS.items()}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def by_lang(words: tuple[str, ...]) -> Column:
    return F.element_at(F.array(*[F.lit(w) for w in words]), F.col("lang_no") + 1)


def by_nation(values: dict[int, str]) -> Column:
    return F.element_at(F.create_map(*[F.lit(x) for kv in values.items() for x in kv]), F.col("nation"))


def label(key: str) -> Column:
    """The key's label, with a plural or a doubled third letter now and then (no label has a blank there)."""
    plain = by_lang(LABELS[key])
    noisy = F.when((F.col("o_orderkey") % 17 == 0) & F.lit(key in ("priority", "quantity", "total")), F.concat(plain, F.lit("s")))
    return noisy.when((F.col("o_orderkey") % 19 == 0) & F.lit(key in ("buyer", "segment", "winner")), F.concat(F.substring(plain, 1, 3), F.substring(plain, 3, 99))).otherwise(plain)


def facts(spark: SparkSession, sf_dir: str, formats: tuple[str, ...] | None = None, layouts: tuple[str, ...] | None = None) -> DataFrame:
    """(o_orderkey, nation, lang, ..., head array<struct<k,l,v>>, lots array<array<struct<k,l,v>>>): what a notice says.

    Format and layout filters are applied to the customers before any join, and only the chosen orders' lots are read on.
    """
    wanted = [k for k in LAYOUTS if (formats is None or FORMATS[k] in formats) and (layouts is None or LAYOUTS[k] in layouts)]
    cust = table(spark, sf_dir, "customer").filter(F.col("c_nationkey").isin(wanted)).select("c_custkey", "c_name", "c_mktsegment", F.col("c_nationkey").alias("nation"))
    place = table(spark, sf_dir, "nation").join(table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("n_nationkey").alias("nation"), "n_name", "r_name")
    orders = table(spark, sf_dir, "orders").join(cust, F.col("o_custkey") == F.col("c_custkey")).join(place, "nation")
    part, supplier = table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_brand"), table(spark, sf_dir, "supplier").select("s_suppkey", "s_name")
    chosen = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey").join(cust.select("c_custkey"), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("l_orderkey")
    line = table(spark, sf_dir, "lineitem")
    line = line.join(chosen, "l_orderkey", "left_semi") if len(wanted) < len(LAYOUTS) else line
    line = line.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    lots = line.groupBy("l_orderkey").agg(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_partkey", "l_suppkey", F.date_format("l_shipdate", "yyyy-MM-dd").alias("shipped"), "p_name", "p_brand", F.col("l_quantity").cast("string").alias("quantity"), F.col("l_extendedprice").cast("string").alias("price"), "s_name"))).alias("raw_lots"))
    base = orders.join(lots, F.col("o_orderkey") == F.col("l_orderkey"), "left").withColumn("lang_no", F.col("nation") % 4).withColumn("lang", by_lang(LANGS)).withColumn("award", F.col("o_orderstatus") == "F")
    base = base.withColumns({"layout": by_nation(LAYOUTS), "format": by_nation(FORMATS)})
    pick = lambda yes, no, test: F.when(test, by_lang(yes)).otherwise(by_lang(no))
    day = F.element_at(F.array(F.date_format("o_orderdate", "yyyy-MM-dd"), F.date_format("o_orderdate", "dd/MM/yyyy"), F.date_format("o_orderdate", "dd.MM.yyyy")), (F.col("o_orderkey") % 3 + 1).cast("int"))
    there = F.col("o_orderkey") % 11 != 0
    values = {
        "reference": F.col("o_orderkey").cast("string"), "kind": pick(AWARD, CALL, F.col("award")), "published": day, "total": F.col("o_totalprice").cast("string"), "priority": F.col("o_orderpriority"),
        "urgent": pick(YES, NO, F.col("o_orderpriority") == "1-URGENT"), "buyer": F.col("c_name"), "segment": F.col("c_mktsegment"), "country": F.when(there, F.col("n_name")), "region": F.when(there, F.col("r_name")),
    }
    field = lambda k, v: F.struct(F.lit(k).alias("k"), label(k).alias("l"), v.alias("v"))
    head = F.filter(F.array(*[field(k, v) for k, v in values.items()]), lambda f: f["v"].isNotNull())

    def lot(x: Column) -> Column:
        got = {"item": x["p_name"], "brand": x["p_brand"], "quantity": x["quantity"], "price": x["price"], "shipped": x["shipped"], "winner": F.when(F.col("award"), x["s_name"])}
        return F.filter(F.array(*[field(k, v) for k, v in got.items()]), lambda f: f["v"].isNotNull())

    return base.withColumn("head", head).withColumn("lots", F.transform(F.coalesce("raw_lots", F.array()), lot))


def escaped(c: Column) -> Column:
    return F.replace(F.replace(F.replace(c, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;")), F.lit(">"), F.lit("&gt;"))


def joined(items: Column, each) -> Column:
    return F.array_join(F.transform(items, each), "")


def tagged(name: Column, text: Column) -> Column:
    return F.concat(F.lit("<"), name, F.lit(">"), escaped(text), F.lit("</"), name, F.lit(">"))


def html_field(style: str, f: Column, i: Column) -> Column:
    l, v = escaped(f["l"]), escaped(f["v"])
    if style == "table":
        return F.concat(F.lit("<tr><td>"), l, F.lit("</td><td>"), v, F.lit("</td></tr>"))
    if style == "sections":
        return F.concat(F.lit("<div><h3>"), F.when(F.col("o_orderkey") % 2 == 0, F.concat(F.lit("I."), (i + 1).cast("string"), F.lit(") "))).otherwise(""), l, F.lit("</h3><p>"), v, F.lit("</p></div>"))
    if style == "widgets":
        return F.when(f["k"].isin("priority", "segment", "kind", "urgent"), F.concat(F.lit("<div><label>"), l, F.lit("</label><select><option>--</option><option selected>"), v, F.lit("</option></select></div>"))).otherwise(F.concat(F.lit("<div><label>"), l, F.lit('</label><input type="text" value="'), v, F.lit('"></div>')))
    sep = F.element_at(F.array(*[F.lit(s) for s in SEPARATORS]), F.when(F.col("nation").between(17, 20), F.col("nation") - 16).otherwise(1))
    return F.concat(F.lit("<p>"), l, sep, v, F.lit("</p>"))


def html_block(style: str, fields: Column) -> Column:
    body = F.array_join(F.transform(fields, lambda f, i: html_field(style, f, i)), "")
    return F.concat(F.lit("<table>"), body, F.lit("</table>")) if style == "table" else F.concat(F.lit("<div>"), body, F.lit("</div>"))


def html_body(style: str) -> Column:
    if style == "mixed":
        top, rest = F.slice("head", 1, 4), F.slice("head", 5, 20)
        head = F.concat(html_block("table", top), html_block("sections", rest))
        lots = joined(F.col("lots"), lambda lot: html_block("flat", lot))
    elif style == "hierarchy":
        buyer, other = F.filter("head", lambda f: f["k"] == "buyer"), F.filter("head", lambda f: f["k"] != "buyer")
        name = F.element_at(F.array(F.lit("Name"), F.lit("Nom"), F.lit("Name"), F.lit("Nombre")), F.col("lang_no") + 1)
        named = lambda title, v: F.concat(F.lit("<div><h2>"), escaped(title), F.lit("</h2><div><h3>"), name, F.lit("</h3><p>"), escaped(v), F.lit("</p></div></div>"))
        head = F.concat(html_block("sections", other), joined(buyer, lambda f: named(by_lang(LABELS["buyer"]), f["v"])))
        lots = joined(F.col("lots"), lambda lot: joined(F.filter(lot, lambda f: f["k"] == "item"), lambda f: named(by_lang(LABELS["item"]), f["v"])))
    else:
        head, lots = html_block(style, F.col("head")), joined(F.col("lots"), lambda lot: html_block(style, lot))
    nav = F.concat(F.lit("<nav><ul>"), joined(F.slice("head", 1, 2), lambda f: F.concat(F.lit("<li>"), escaped(f["l"]), F.lit("</li><li>all</li>"))), F.lit("</ul></nav>"))
    return F.concat(F.lit('<html lang="'), F.col("lang"), F.lit('"><head><title>Notice '), F.col("o_orderkey").cast("string"), F.lit("</title></head><body>"), nav, F.lit('<main id="notice">'), head, lots, F.lit("</main></body></html>"))


def xml_body(layout: str) -> Column:
    el = lambda f: tagged(f["k"], f["v"])
    head = joined(F.col("head"), el)
    if layout == "xml_numbered":
        lots = F.array_join(F.transform("lots", lambda lot, i: F.concat(F.lit("<lot_"), (i + 1).cast("string"), F.lit(">"), joined(lot, el), F.lit("</lot_"), (i + 1).cast("string"), F.lit(">"))), "")
    elif layout == "xml_nested":
        # lot fields as item_1, brand_1, ... beside each other under one element
        lots = F.array_join(F.transform("lots", lambda lot, i: joined(lot, lambda f: tagged(F.concat(F.lit("lot_"), (i + 1).cast("string"), F.lit("_"), f["k"]), f["v"]))), "")
    else:
        lots = F.array_join(F.transform("lots", lambda lot, i: F.concat(F.lit('<lot no="'), (i + 1).cast("string"), F.lit('">'), joined(lot, el), F.lit("</lot>"))), "")
    return F.concat(F.lit('<notice lang="'), F.col("lang"), F.lit('"><head>'), head, F.lit("</head><lots>"), lots, F.lit("</lots></notice>"))


def csv_body() -> Column:
    """A header row and one row for each lot (one without lot fields if there are none)."""
    line = lambda fields: F.array_join(F.transform(fields, lambda f: F.concat(F.lit('"'), F.replace(f["v"], F.lit('"'), F.lit('""')), F.lit('"'))), ",")
    every = F.array(*[F.lit(k) for k in (*HEAD, *LOT)])
    value = lambda fields, k: F.coalesce(F.element_at(F.transform(F.filter(fields, lambda f: f["k"] == k), lambda f: f["v"]), 1), F.lit(""))
    cell = lambda fields: F.transform(every, lambda k: F.struct(F.try_element_at(F.transform(F.filter(fields, lambda f: f["k"] == k), lambda f: f["v"]), F.lit(1)).alias("v")))
    filled = lambda fields: F.transform(cell(fields), lambda f: F.struct(F.coalesce(f["v"], F.lit("")).alias("v")))
    rows = F.transform(F.when(F.size("lots") > 0, F.col("lots")).otherwise(F.array(F.expr("filter(head, f -> false)"))), lambda lot: line(filled(F.concat(F.col("head"), lot))))
    return F.concat(F.array_join(every, ","), F.lit("\n"), F.array_join(rows, "\n"))


def notices(spark: SparkSession, sf_dir: str, formats: tuple[str, ...] | None = None, layouts: tuple[str, ...] | None = None) -> DataFrame:
    """(doc_id, source, nation, lang, format, layout, content_type, body, captured_at): the rendered corpus."""
    f = facts(spark, sf_dir, formats, layouts)
    kinds = sorted({v for v in LAYOUTS.values() if (layouts is None or v in layouts)} & ({LAYOUTS[k] for k in LAYOUTS if formats is None or FORMATS[k] in formats}))
    bodies = [(F.col("layout") == k, xml_body(k) if k.startswith("xml") else csv_body() if k == "csv" else html_body(k)) for k in kinds]
    body = reduce(lambda acc, x: acc.when(*x), bodies[1:], F.when(*bodies[0]))
    mime = F.concat(F.when(F.col("format") == "xml", "application/xml").when(F.col("format") == "csv", "text/csv").otherwise("text/html"), F.lit("; charset=utf-8"))
    return f.select(F.col("o_orderkey").cast("string").alias("doc_id"), F.col("n_name").alias("source"), "nation", "lang", "format", "layout", mime.alias("content_type"), body.alias("body"), F.col("o_orderdate").alias("captured_at"))


def dictionary(spark: SparkSession, keys: tuple[str, ...] = (*HEAD, *LOT)) -> DataFrame:
    """(lang, key_id, parent_key_id, surface, elem_name, is_static): one surface for each key and language."""
    rows = [(lang, k, None, LABELS[k][i], k, False) for k in keys for i, lang in enumerate(LANGS)]
    return spark.createDataFrame(rows, "lang string, key_id string, parent_key_id string, surface string, elem_name string, is_static boolean")


def name_dictionary(spark: SparkSession) -> DataFrame:
    """Hierarchical entries: a leaf "name" under the buyer and under the item."""
    names = ("Name", "Nom", "Name", "Nombre")
    rows = [(lang, f"{p}/name", p, names[i], "name", False) for p in ("buyer", "item") for i, lang in enumerate(LANGS)]
    return dictionary(spark).union(spark.createDataFrame(rows, dictionary(spark).schema))
