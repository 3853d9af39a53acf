"""Tolerant HTML and XML shredding into ordered text-bearing nodes with three path spellings.

The parser runs once per document inside one Arrow pass that emits node rows, so no optimizer rule can evaluate it
twice and only the id columns named by the caller travel along.
"""

from __future__ import annotations

import re
from collections import defaultdict
from collections.abc import Iterator
from html.entities import html5
from html.parser import HTMLParser
from xml.parsers import expat

import pyarrow as pa
from pyspark.sql import DataFrame

#: Elements without content, elements whose text is not content, implied ends.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
SKIP = frozenset(("script", "style", "template"))
ENDS = {"li": ("li",), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr", "td", "th"), "option": ("option",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "p": ("p",)}
BLOCKS = frozenset("address article aside blockquote div dl fieldset footer form h1 h2 h3 h4 h5 h6 header hr main nav ol p pre section table ul".split())
IDENTITY = ("id", "class", "name")
_REFERENCE = re.compile(r"&(#[0-9]+;|#[xX][0-9a-fA-F]+;|[A-Za-z][A-Za-z0-9]*;)?")
NODE = "ord int, depth int, tag string, plain array<string>, numbered array<string>, attributed array<string>, attrs map<string,string>, text string"
_NODE_TYPES = [pa.int32(), pa.int32(), pa.string(), pa.list_(pa.string()), pa.list_(pa.string()), pa.list_(pa.string()), pa.map_(pa.string(), pa.string()), pa.string()]


class Tree:
    """Open elements and the nodes seen so far; shared by both parsers."""

    def __init__(self, numbering: str = "global", number_leaf: bool = False):
        self.numbering, self.number_leaf = numbering, number_leaf
        self.open: list[tuple[str, str, str, dict]] = []  # tag, numbered, attributed, attributes
        self.children: list[dict] = [defaultdict(int)]
        self.seen: dict[str, int] = defaultdict(int)
        self.nodes: list[tuple] = []
        self.skip = 0

    def push(self, tag: str, attrs: dict) -> None:
        siblings = self.children[-1]
        siblings[tag] += 1
        self.seen[tag] += 1
        numbered = f"{tag}{self.seen[tag] if self.numbering == 'global' else siblings[tag]}"
        ident = next((attrs[k] for k in IDENTITY if attrs.get(k)), "")
        self.open.append((tag, numbered, f"{numbered}.{ident}" if ident else numbered, attrs))
        self.children.append(defaultdict(int))
        self.skip += tag in SKIP

    def pop_to(self, at: int) -> None:
        for tag, *_ in self.open[at:]:
            self.skip -= tag in SKIP
        del self.open[at:], self.children[at + 1 :]

    def text(self, data: str) -> None:
        data = " ".join(data.split())
        if data and not self.skip:
            self.add(data)

    def add(self, data: str) -> None:
        leaf = self.open[-1] if self.open else ("", "", "", {})
        numbered = [e[1] for e in self.open]
        attributed = [e[2] for e in self.open]
        if self.open and not self.number_leaf:
            numbered[-1] = leaf[0]
            attributed[-1] = leaf[0] + (attributed[-1][len(leaf[1]) :])
        self.nodes.append((len(self.nodes), len(self.open), leaf[0], [e[0] for e in self.open], numbered, attributed, list(leaf[3].items()), data))


class _Html(HTMLParser):
    def __init__(self, tree: Tree, simplify: bool):
        super().__init__(convert_charrefs=True)
        self.tree, self.simplify, self.parts = tree, simplify, []

    def flush(self):
        if self.parts:
            data = "".join(self.parts)
            self.parts.clear()
            open_ = self.tree.open
            if self.simplify and open_ and open_[-1][0] == "option" and "selected" not in open_[-1][3]:
                return  # of a form list only what is selected says something
            self.tree.text(data)

    def handle_starttag(self, tag, attrs):
        self.flush()
        attrs = {k: v or "" for k, v in attrs}
        tree = self.tree
        if tag in VOID:
            if tag == "input" and self.simplify and attrs.get("value") and attrs.get("type", "text") in ("text", "number", "date"):
                tree.push(tag, attrs)
                tree.text(attrs["value"])
                tree.pop_to(len(tree.open) - 1)
            return
        if tag in BLOCKS:
            for k in range(len(tree.open) - 1, -1, -1):
                if tree.open[k][0] == "p":
                    tree.pop_to(k)
                    break
                if tree.open[k][0] in BLOCKS or tree.open[k][0] in ("td", "th", "li"):
                    break
        if tag in ENDS:
            for k in range(len(tree.open) - 1, -1, -1):
                if tree.open[k][0] in ENDS[tag]:
                    tree.pop_to(k)
                    if tag != "tr":
                        break
                elif tree.open[k][0] in ("table", "ul", "ol", "dl", "select") or tree.open[k][0] in BLOCKS:
                    break
        tree.push(tag, attrs)

    def handle_startendtag(self, tag, attrs):
        self.handle_starttag(tag, attrs)
        if tag not in VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        self.flush()
        for k in range(len(self.tree.open) - 1, -1, -1):
            if self.tree.open[k][0] == tag:
                self.tree.pop_to(k)
                return

    def handle_data(self, data):
        self.parts.append(data)


def closed_references(html: str) -> str:
    """Escapes every ampersand that begins no reference with its semicolon, so that a parser leaves it as it stands."""
    return _REFERENCE.sub(lambda m: m[0] if m[1] and (m[1][0] == "#" or m[1] in html5) else "&amp;" + m[0][1:], html)


def html_nodes(html: str | None, numbering: str = "global", number_leaf: bool = False, simplify: bool = False, closed: bool = False) -> list[tuple]:
    """Text-bearing nodes of tag soup in document order. References without their semicolon (a text cut off in one) are decoded as
    browsers do; with closed they stay as they stand."""
    tree = Tree(numbering, number_leaf)
    if html:
        html = closed_references(html) if closed else html
        parser = _Html(tree, simplify)
        parser.feed(html)
        parser.close()
        parser.flush()
    return tree.nodes


def xml_nodes(xml: str | bytes | None, numbering: str = "global", attributes: bool = True) -> list[tuple] | None:
    """Nodes of well-formed XML, attributes as nodes with a last step @name; None if it is not well-formed."""
    tree = Tree(numbering)
    parts: list[str] = []
    parser = expat.ParserCreate()
    parser.buffer_text = True

    def flush():
        if parts:
            tree.text("".join(parts))
            parts.clear()

    def start(tag, attrs):
        flush()
        tree.push(tag, attrs)
        for k, v in attrs.items() if attributes else ():
            if v.strip():
                n = len(tree.open)
                base = [e[0] for e in tree.open], [e[1] for e in tree.open]
                tree.nodes.append((len(tree.nodes), n + 1, f"@{k}", [*base[0], f"@{k}"], [*base[1], f"@{k}"], [*base[1], f"@{k}"], [], v.strip()))

    def end(tag):
        flush()
        tree.pop_to(len(tree.open) - 1)

    parser.StartElementHandler, parser.EndElementHandler, parser.CharacterDataHandler = start, end, parts.append
    try:
        parser.Parse(xml or "", True)
    except expat.ExpatError:
        return None
    return tree.nodes


FIELDS = tuple(x.split()[0] for x in NODE.split(", "))


def node_table(docs: DataFrame, body: str, keep: tuple[str, ...], kind: str = "html", max_nodes: int | None = None, fields: tuple[str, ...] = FIELDS, **options) -> DataFrame:
    """One row for each node: the keep columns and the node's fields. XML that does not parse gives one row with a null ord.

    Only the named fields leave Python: no later pruning can take back a path spelling once it is built.
    max_nodes, if set, stops very large documents; the row after the last kept node then has the text null.
    """
    wanted = [FIELDS.index(f) for f in fields]
    schema = ", ".join([f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep] + [NODE.split(", ")[k] for k in wanted])
    names = [*keep, *fields]
    parse = html_nodes if kind == "html" else xml_nodes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 200):
                part = batch.slice(at, 200)
                rows: list[tuple] = []
                owner: list[int] = []
                for i, text in enumerate(part.column(len(keep)).to_pylist()):
                    nodes = parse(text, **options)
                    if nodes is None:
                        nodes = [(None, None, None, None, None, None, None, None)]
                    elif max_nodes is not None and len(nodes) > max_nodes:
                        nodes = [*nodes[:max_nodes], (max_nodes, None, None, None, None, None, None, None)]
                    rows += nodes
                    owner += [i] * len(nodes)
                index = pa.array(owner, pa.int32())
                kept = [part.column(k).take(index) for k in range(len(keep))]
                columns = [pa.array([r[k] for r in rows], _NODE_TYPES[k]) for k in wanted]
                yield pa.RecordBatch.from_arrays([*kept, *columns], names)

    return docs.select(*keep, body).mapInArrow(run, schema)
