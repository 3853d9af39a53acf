"""Format-normalising chains: a registry of named stages, unpacking, trees from CSV, JSON and text, element repairs, batches."""

from __future__ import annotations

import csv
import gzip
import io
import json
import tarfile
import zipfile
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.shred import NODE

STAGES: dict[str, Callable[..., DataFrame]] = {}


def register_stage(name: str, fn: Callable[..., DataFrame]) -> None:
    if name in STAGES and STAGES[name] is not fn:
        raise ValueError(f"stage {name} is already registered")
    STAGES[name] = fn


def run_chain(docs: DataFrame, spec: dict[str, list], phase: str) -> DataFrame:
    """Applies a source's stages of one phase (load, pre, post) in order, as one lazy plan. A stage is a name or [name, options]."""
    for step in spec.get(phase, []):
        name, options = (step, {}) if isinstance(step, str) else step
        docs = docs.transform(STAGES[name], **options)
    return docs


# unpacking

_MEMBER = "item_id string, member string, status string, body binary"


def members(name: str, data: bytes) -> Iterator[tuple[str, str, bytes | None]]:
    """(member, status, bytes) of an archive; anything else is its own only member; unreadable ones are flagged."""
    try:
        if data[:2] == b"PK":
            with zipfile.ZipFile(io.BytesIO(data)) as z:
                yield from ((i.filename, "ok", z.read(i)) for i in z.infolist() if not i.is_dir())
        elif data[:2] == b"\x1f\x8b" or data[257:262] == b"ustar":
            raw = gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data
            if raw[257:262] == b"ustar":
                with tarfile.open(fileobj=io.BytesIO(raw)) as t:
                    yield from ((m.name, "ok", t.extractfile(m).read()) for m in t if m.isfile())
            else:
                yield name.removesuffix(".gz"), "ok", raw
        elif data[:4] == b"Rar!":
            yield name, "unsupported", None
        elif data[:4] in (b"%PDF", b"\xd0\xcf\x11\xe0"):
            yield name, "unsupported", None
        else:
            yield name, "ok", data
    except (zipfile.BadZipFile, tarfile.TarError, OSError, EOFError) as e:
        yield name, f"damaged: {type(e).__name__}", None


def unpack(items: DataFrame) -> DataFrame:
    """(item_id, member, status, body): archive members of (item_id, name, body), one row each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i, n, x in zip(*(b.column(k).to_pylist() for k in range(3))):
                rows = [(i, *m) for m in members(n or "", x or b"")]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 4, (pa.string(), pa.string(), pa.string(), pa.binary()))], [x.split()[0] for x in _MEMBER.split(", ")])

    return items.select("item_id", "name", "body").mapInArrow(run, _MEMBER)


# trees from flat formats


def record_nodes(records: Column, root: str, row: str) -> Column:
    """Node array of an array of maps: /root/row/<field>."""
    flat = F.flatten(F.transform(records, lambda m, i: F.transform(F.map_entries(m), lambda e: F.struct(i.alias("i"), e["key"].alias("k"), e["value"].alias("v")))))
    kept = F.filter(flat, lambda x: F.length(F.trim(x["v"])) > 0)
    text = lambda *xs: F.array(*[F.lit(x) if isinstance(x, str) else x for x in xs])
    return F.transform(kept, lambda x, n: F.struct(
        n.cast("int").alias("ord"), F.lit(3).alias("depth"), x["k"].alias("tag"), text(root, row, x["k"]).alias("plain"),
        text(root + "1", F.concat(F.lit(row), (x["i"] + 1).cast("string")), x["k"]).alias("numbered"), text(root + "1", F.concat(F.lit(row), (x["i"] + 1).cast("string")), x["k"]).alias("attributed"),
        F.create_map().cast("map<string,string>").alias("attrs"), F.trim(x["v"]).alias("text")))


def csv_to_tree(docs: DataFrame, body: str = "body", sep: str = ",", root: str = "rows", row: str = "row") -> DataFrame:
    """Node rows of CSV bodies; header names become element names. Quoted cells may hold separators and line ends."""
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in ("doc_id", "source", "lang"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = []
            for text in b.column(3).to_pylist():
                lines = csv.reader(io.StringIO(text or ""), delimiter=sep)
                head = [h.strip() for h in next(lines, [])]
                got.append([[(h, v) for h, v in zip(head, line) if h] for line in lines])
            yield pa.RecordBatch.from_arrays([*[b.column(k) for k in range(3)], pa.array(got, pa.list_(pa.map_(pa.string(), pa.string())))], ["doc_id", "source", "lang", "records"])

    parsed = docs.select("doc_id", "source", "lang", body).mapInArrow(run, f"{schema}, records array<map<string,string>>")
    return parsed.select("doc_id", "source", "lang", F.inline(record_nodes(F.col("records"), root, row)))


def json_to_tree(docs: DataFrame, body: str = "body") -> DataFrame:
    """Node rows of JSON bodies: object members are steps, list items repeat their step; unreadable JSON gives no rows."""
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in ("doc_id", "source", "lang"))

    def leaves(x, steps, numbered, counts):
        if isinstance(x, dict):
            for k, v in x.items():
                for item in v if isinstance(v, list) else [v]:
                    counts[k] = counts.get(k, 0) + 1
                    yield from leaves(item, [*steps, k], [*numbered, f"{k}{counts[k]}"], counts)
        elif isinstance(x, list):
            for item in x:
                yield from leaves(item, steps, numbered, counts)
        elif x is not None and str(x).strip():
            yield steps, numbered, str(x).lower() if isinstance(x, bool) else str(x)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, owner = [], []
            for i, text in enumerate(b.column(3).to_pylist()):
                try:
                    tree = json.loads(text or "null")
                except ValueError:
                    continue
                for n, (steps, numbered, value) in enumerate(leaves(tree, ["json"], ["json1"], {})):
                    low = [*numbered[:-1], steps[-1]]
                    rows.append((n, len(steps), steps[-1], steps, low, low, [], value))
                    owner.append(i)
            kinds = [pa.int32(), pa.int32(), pa.string(), *[pa.list_(pa.string())] * 3, pa.map_(pa.string(), pa.string()), pa.string()]
            index = pa.array(owner, pa.int32())
            yield pa.RecordBatch.from_arrays([*[b.column(k).take(index) for k in range(3)], *[pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * 8, kinds)]], ["doc_id", "source", "lang", *[x.split()[0] for x in NODE.split(", ")]])

    return docs.select("doc_id", "source", "lang", body).mapInArrow(run, f"{schema}, {NODE}")


def txt_to_tree(docs: DataFrame, body: str = "body") -> DataFrame:
    """Node rows of plain text: one /text/line node for each line that is not blank."""
    lines = F.transform(F.split(body, r"\r?\n"), lambda x: F.create_map(F.lit("line"), x))
    return docs.select("doc_id", "source", "lang", F.inline(record_nodes(lines, "text", "p")))


# repairs


def wellformed(nodes: DataFrame) -> DataFrame:
    """(doc_id, wellformed): shredded XML that did not parse has one row without an ordinal."""
    return nodes.groupBy("doc_id").agg(F.bool_and(F.col("ord").isNotNull()).alias("wellformed"))


def fold_numbered(nodes: DataFrame, patterns: tuple[str, ...] = (r"^(.*?)_(\d+)()$",)) -> DataFrame:
    """Numbered siblings become one repeated element: the number leaves the plain step and stays in the numbered one.

    Each pattern has groups prefix, number, suffix; numbers between prefix and suffix are patterns of their own.
    """

    def fold(step: Column) -> Column:
        for p in patterns:
            step = F.when(F.regexp_extract(step, p, 2) != "", F.concat(F.regexp_extract(step, p, 1), F.regexp_extract(step, p, 3))).otherwise(step)
        return step

    return nodes.withColumns({"plain": F.transform("plain", fold), "tag": fold(F.col("tag"))})


def nest_numbered(nodes: DataFrame, pattern: str = r"^(.*?)_(\d+)_(.+)$") -> DataFrame:
    """A numbered hierarchy in one step (lot_3_item) becomes nested elements (lot with number 3, item in it)."""
    parts = lambda s: F.when(F.regexp_extract(s, pattern, 2) != "", F.array(F.regexp_extract(s, pattern, 1), F.regexp_extract(s, pattern, 3))).otherwise(F.array(s))
    # a numbered step already has its own counter at its end, so the pattern's number is enough to tell instances apart
    numbered = lambda s: F.when(F.regexp_extract(s, pattern, 2) != "", F.array(F.concat(F.regexp_extract(s, pattern, 1), F.regexp_extract(s, pattern, 2)), F.regexp_extract(s, pattern, 3))).otherwise(F.array(s))
    out = nodes.withColumns({c: F.flatten(F.transform(c, parts if c == "plain" else numbered)) for c in ("plain", "numbered", "attributed") if c in nodes.columns})
    return out.withColumns({"tag": F.element_at("plain", -1), "depth": F.size("plain")})


def cleanup(spark, path: str) -> bool:
    """Deletes a run's own intermediate folder through Hadoop's file system."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)


def plan_batches(items: DataFrame, target_bytes: int, order: str = "fifo") -> DataFrame:
    """(item_id, bytes, batch): small items grouped up to a size; fifo keeps the order of arrival, longest puts big ones first."""
    key = [F.col("captured_at"), F.col("item_id")] if order == "fifo" else [F.col("bytes").desc(), F.col("item_id")]
    sized = items.withColumn("bytes", F.octet_length("body"))
    w = Window.partitionBy("source").orderBy(*key).rowsBetween(Window.unboundedPreceding, -1)
    return sized.withColumn("batch", F.floor(F.coalesce(F.sum("bytes").over(w), F.lit(0)) / target_bytes)).select("source", "item_id", "bytes", "batch")


def to_utf8(items: DataFrame) -> DataFrame:
    """Bodies as UTF-8 text (item_id, charset, agreed, text) beside their other columns: the charset chain as a stage."""
    from .archive import resolve_charsets

    return items.drop("text", "charset", "agreed").join(resolve_charsets(items), "item_id")


for _name, _fn in {"utf8": to_utf8, "unpack": unpack, "fold_numbered": fold_numbered, "nest_numbered": nest_numbered, "csv": csv_to_tree, "json": json_to_tree, "txt": txt_to_tree}.items():
    register_stage(_name, _fn)
