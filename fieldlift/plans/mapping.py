"""Target schemas, mappings, path expressions: specifications read on the driver and compiled to column expressions."""

from __future__ import annotations

import json
import re
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..functions.columns import path_text, text_sim

TYPES = {"text": T.StringType(), "date": T.TimestampNTZType(), "boolean": T.BooleanType(), "integer": T.LongType(), "number": T.DoubleType(), "money": T.DecimalType(18, 2), "link": T.LongType()}


@dataclass(frozen=True)
class Entity:
    name: str
    fields: dict[str, str]  # name -> type
    links: dict[str, str] = field(default_factory=dict)  # column -> entity it points to
    repeats: bool = False
    label: str = ""


@dataclass(frozen=True)
class Target:
    entities: dict[str, Entity]

    def structs(self) -> dict[str, T.StructType]:
        return {n: T.StructType([T.StructField("id", T.LongType(), False), *[T.StructField(k, TYPES[t]) for k, t in e.fields.items()], *[T.StructField(k, T.LongType()) for k in e.links]]) for n, e in self.entities.items()}


def load_target(text: str) -> Target:
    """Reads {entities: [{name, label, repeats, fields: {name: type}, links: {column: entity}}]}; unknown types and links are errors."""
    found = {}
    for e in json.loads(text)["entities"]:
        bad = [t for t in e.get("fields", {}).values() if t not in TYPES]
        if bad or e["name"] in found:
            raise ValueError(f"{e['name']}: {'unknown types ' + ', '.join(bad) if bad else 'named twice'}")
        found[e["name"]] = Entity(e["name"], e.get("fields", {}), e.get("links", {}), e.get("repeats", False), e.get("label", e["name"]))
    for e in found.values():
        if missing := [t for t in e.links.values() if t not in found]:
            raise ValueError(f"{e.name}: no entity {', '.join(missing)}")
    return Target(found)


@dataclass(frozen=True)
class PathExpr:
    """A path over element steps: child steps, @attribute, text(), [k], // and *, and step names as ~pattern."""

    text: str
    pattern: str
    index: int | None
    plain: bool

    def matches(self, path: Column) -> Column:
        return (path == self.text) if self.plain else path.rlike(self.pattern)


def compile_path(text: str) -> PathExpr:
    index = int(m[1]) if (m := re.search(r"\[(\d+)\]$", text)) else None
    core = re.sub(r"\[\d+\]$", "", text)
    core = re.sub(r"/text\(\)$", "", core)
    plain = not re.search(r"//|\*|~", core)
    pattern = "^"
    for sep, step in re.findall(r"(//?)([^/]+)", core if core.startswith("/") else "/" + core):
        one = "[^/]+" if step == "*" else step[1:] if step.startswith("~") else re.escape(step)
        pattern += ("(?:/[^/]+)*/" if sep == "//" else "/") + f"(?:{one})"
    return PathExpr(core, pattern + "$", index, plain)


@dataclass(frozen=True)
class Node:
    """One entity of a mapping: its occurrences, fields with alternative paths, recodes and nested entities."""

    entity: str
    path: str
    fields: dict[str, list[str]]
    recodes: dict[str, dict[str, str]]
    children: tuple[Node, ...] = ()
    link: str = "up"  # up: the child points to its parent; down: the parent points to the child
    column: str = ""


@dataclass(frozen=True)
class Mapping:
    version: int
    roots: tuple[Node, ...]

    def walk(self):
        """(node, absolute path, role, parent role, parent depth) of every entity, parents first."""

        def go(n: Node, base: str, role: str, parent: tuple[str, int] | None, node_parent: Node | None):
            path = n.path if n.path.startswith("/") else base if n.path == "." else f"{base}/{n.path}"
            here = f"{role}/{n.column or n.entity}" if role else n.entity
            yield n, path, here, parent, node_parent
            for c in n.children:
                yield from go(c, path, here, (here, path.count("/")), n)

        for r in self.roots:
            yield from go(r, "", "", None, None)


def load_mapping(text: str) -> Mapping:
    def node(d: dict) -> Node:
        fields = {k: [v] if isinstance(v, str) else list(v) for k, v in d.get("fields", {}).items()}
        return Node(d["entity"], d.get("path", "."), fields, d.get("recodes", {}), tuple(node(c) for c in d.get("children", [])), d.get("link", "up"), d.get("column", ""))

    spec = json.loads(text)
    return Mapping(spec.get("version", 1), tuple(node(d) for d in spec["map"]))


def absolute(base: str, path: str) -> str:
    return path if path.startswith("/") else f"{base}/{path}"


def merge_mappings(a: Mapping, b: Mapping) -> Mapping:
    """Both mappings' paths and recodes; a's alternatives come first, entities are matched by name and place."""

    def both(x: Node, y: Node) -> Node:
        fields = {k: list(dict.fromkeys([*x.fields.get(k, []), *y.fields.get(k, [])])) for k in {**x.fields, **y.fields}}
        recodes = {k: {**y.recodes.get(k, {}), **x.recodes.get(k, {})} for k in {**x.recodes, **y.recodes}}
        return replace(x, fields=fields, recodes=recodes, children=several(x.children, y.children))

    def several(xs, ys):
        key = lambda n: (n.entity, n.path, n.column)
        theirs = {key(n): n for n in ys}
        return tuple(both(n, theirs.pop(key(n))) if key(n) in theirs else n for n in xs) + tuple(theirs.values())

    return Mapping(max(a.version, b.version) + 1, several(a.roots, b.roots))


def mapped_paths(spark: SparkSession, mapping: Mapping) -> DataFrame:
    """(entity, field, path, pattern) of everything the mapping names."""
    rows = [(n.entity, f, absolute(p, x), compile_path(absolute(p, x)).pattern) for n, p, *_ in mapping.walk() for f, xs in n.fields.items() for x in xs]
    return spark.createDataFrame(rows, "entity string, field string, path string, pattern string")


def lint_mapping(spark: SparkSession, mapping: Mapping, target: Target, inventory: DataFrame) -> DataFrame:
    """(kind, entity, field, detail): dead paths, fields without a path, fields the target does not have."""
    named = mapped_paths(spark, mapping)
    # the mapping's own paths are a driver-side list, so they are the side to broadcast
    live = inventory.select("path").distinct().withColumnRenamed("path", "seen").join(F.broadcast(named), F.expr("seen rlike pattern")).select("entity", "field", "path").distinct()
    dead = named.join(live, ["entity", "field", "path"], "left_anti").select(F.lit("dead path").alias("kind"), "entity", "field", F.col("path").alias("detail"))
    have = {(n.entity, f) for n, *_ in mapping.walk() for f in n.fields}
    rows = [("unmapped field", e.name, f, t) for e in target.entities.values() for f, t in e.fields.items() if (e.name, f) not in have]
    rows += [("unknown field", e, f, "") for e, f in sorted(have) if e not in target.entities or f not in target.entities[e].fields]
    extra = spark.createDataFrame(rows, "kind string, entity string, field string, detail string")
    return dead.unionByName(extra)


def suggest(spark: SparkSession, mapping: Mapping, target: Target, inventory: DataFrame, k: int = 3) -> DataFrame:
    """(entity, field, path, sim): for unmapped fields the k paths whose last step looks most like their name."""
    have = {(n.entity, f) for n, *_ in mapping.walk() for f in n.fields}
    want = spark.createDataFrame([(e.name, f) for e in target.entities.values() for f in e.fields if (e.name, f) not in have], "entity string, field string")
    paths = inventory.select("path").distinct().withColumn("step", F.regexp_replace(F.element_at(F.split("path", "/"), -1), "^@", ""))
    scored = F.broadcast(want).join(paths, F.lit(True)).withColumn("sim", text_sim(F.lower("field"), F.lower("step")))
    best = Window.partitionBy("entity", "field").orderBy(F.col("sim").desc(), "path")
    return scored.withColumn("r", F.row_number().over(best)).filter(F.col("r") <= k).select("entity", "field", "path", "sim")


def record_kind(nodes: DataFrame, path: str, words: dict[str, tuple[str, ...]]) -> DataFrame:
    """(doc_id, record_kind): the kind whose words (of any language) a document's first hit of the path names; null if none does."""
    known = [(w.lower(), kind) for kind, several in words.items() for w in dict.fromkeys(several)]
    table = F.create_map(*[F.lit(x) for pair in known for x in pair])
    hits = nodes.filter(compile_path(path).matches(path_text("plain")))
    first = hits.groupBy("doc_id").agg(F.min_by("text", "ord").alias("word"))
    return first.select("doc_id", F.try_element_at(table, F.lower(F.trim("word"))).alias("record_kind"))
