"""Extraction of entity instances from shredded documents, ids, ordered flushes and integrity checks.

The recursion of a mapping is unrolled on the driver into a lookup table: for each path the instances it fills, the pointers
between them and the ancestors it keeps alive. Every node row meets that table once by its path, in a broadcast join that drops
the nodes no wanted entity needs. One aggregation by instance then builds all instances; unfilled ones never exist.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.columns import path_text, to_bool, to_date_any
from ..operators.dictionary import _cut
from .mapping import Mapping, Target, absolute, compile_path


def content_id(doc: Column, role: str | Column, place: Column) -> Column:
    """A stable 64-bit id from document, role and numbered place."""
    return F.xxhash64(doc, F.lit(role) if isinstance(role, str) else role, place)


def place(depth: Column) -> Column:
    """The numbered path of a node's ancestor at that depth. The leaf of a numbered path has no number, so an instance that
    is itself the node gets the node's ordinal."""
    return F.when(F.size("plain") > depth, F.array_join(F.slice("numbered", F.lit(1), depth), "/")).otherwise(F.concat_ws("#", F.array_join("numbered", "/"), F.col("ord").cast("string")))


LOOKUP = "step string, role string, depth int, field string, prio int, to_role string, to_depth int, recodes map<string,string>"


def lookup_rows(mapping: Mapping, entities: set[str] | None = None) -> list[tuple]:
    """Rows of the lookup table for the wanted entities: what a node on a path says about an instance.

    step is a plain path, or the pattern of a path with wildcards. A row fills a field, sets a pointer (to_role) or only keeps
    an ancestor alive (field empty).
    """
    roles = {role: (n, base, parent, up) for n, base, role, parent, up in mapping.walk()}
    rows: dict[tuple, tuple] = {}

    def add(step: str, role: str, depth: int, name: str, prio: int, to_role: str | None = None, to_depth: int | None = None, recodes: dict | None = None) -> None:
        if entities is None or roles[role][0].entity in entities:
            rows.setdefault((step, role, name, prio, to_role), (step, role, depth, name, prio, to_role, to_depth, recodes or None))

    for role, (n, base, _, _) in roles.items():
        for name, alternatives in n.fields.items():
            for prio, alt in enumerate(alternatives):
                expr = compile_path(absolute(base, alt))
                step = expr.text if expr.plain else expr.pattern
                add(step, role, base.count("/"), name, prio, recodes=n.recodes.get(name))
                child = role
                while (parent := roles[child][2]) is not None:
                    cn, cp, _, up = roles[child]
                    cd, (pr, pd) = cp.count("/"), parent
                    if cn.link == "down":
                        add(step, pr, pd, cn.column or f"{cn.entity}_id", 0, child, cd)
                    else:
                        add(step, child, cd, f"{up.entity}_id", 0, pr, pd)
                        add(step, pr, pd, "", 0)
                    child = pr
    return list(rows.values())


def filled_rows(nodes: DataFrame, mapping: Mapping, entities: set[str] | None = None) -> DataFrame:
    """(doc_id, source, lang, role, id, field, prio, ord, value): what each node says about each instance."""
    rows = lookup_rows(mapping, entities)
    # made on the driver from the mapping: a few rows for each of its paths
    table = F.broadcast(nodes.sparkSession.createDataFrame(rows, LOOKUP))
    patterns = sorted({r[0] for r in rows if r[0].startswith("^")})
    path = path_text("plain")
    steps = F.array(path, *[F.when(path.rlike(p), F.lit(p)) for p in patterns])
    kept = nodes.filter(F.trim("text") != "").select("doc_id", "source", "lang", "ord", "text", "plain", "numbered", (F.explode(F.filter(steps, lambda x: x.isNotNull())) if patterns else path).alias("step"))
    met = kept.join(table, "step")
    doc = F.col("doc_id")
    text = F.when(F.col("recodes").isNull(), F.col("text")).otherwise(F.coalesce(F.try_element_at("recodes", F.col("text")), F.col("text")))
    value = F.when(F.col("to_role").isNotNull(), content_id(doc, F.col("to_role"), place(F.col("to_depth"))).cast("string")).when(F.col("field") != "", text)
    return met.select("doc_id", "source", "lang", "role", content_id(doc, F.col("role"), place(F.col("depth"))).alias("id"), "field", "prio", "ord", value.alias("value"))


def count_instances(nodes: DataFrame, mapping: Mapping) -> DataFrame:
    """(source, entity, rows) without building the instances: distinct (entity, id), counted by source; 0 where a source has none."""
    names = {role: n.entity for n, _, role, *_ in mapping.walk()}
    spark = nodes.sparkSession
    entity = F.broadcast(spark.createDataFrame(list(names.items()), "role string, entity string"))
    ids = filled_rows(nodes, mapping).select("source", "role", "id").distinct().join(entity, "role")
    found = ids.groupBy("source").pivot("entity", sorted(set(names.values()))).agg(F.count(F.lit(1)))
    cells = F.array(*[F.struct(F.lit(n).alias("entity"), F.coalesce(F.col(n), F.lit(0)).cast("long").alias("rows")) for n in sorted(set(names.values()))])
    return found.select("source", F.inline(cells))


def extract_entities(nodes: DataFrame, mapping: Mapping, target: Target, only: tuple[str, ...] | None = None) -> dict[str, DataFrame]:
    """One DataFrame for each entity (or those named): id, doc_id, source, lang, its fields as text and its links as ids.

    Where several entities are wanted, documents are shredded and looked up once and the rows cut off in the shared folder.
    """
    rows = filled_rows(nodes, mapping, set(only) if only is not None else None)
    rows = rows if only is not None and len(only) == 1 else _cut(rows)
    by_entity: dict[str, list[str]] = {}
    for n, _, role, *_ in mapping.walk():
        by_entity.setdefault(n.entity, []).append(role)
    out = {}
    for entity, roles in by_entity.items():
        if only is not None and entity not in only:
            continue
        spec = target.entities[entity]
        mine = rows.filter(F.col("role").isin(roles))
        pick = lambda f: F.min(F.when(F.col("field") == f, F.struct("prio", "ord", "value")))["value"]
        columns = [pick(f).alias(f) for f in spec.fields] + [pick(f).cast("long").alias(f) for f in spec.links]
        out[entity] = mine.groupBy("id", "doc_id", "source", "lang").agg(*columns)
    return out


def extract_by_kind(nodes: DataFrame, kinds: DataFrame, branches: dict[str, Mapping], target: Target) -> dict[str, DataFrame]:
    """Entities of documents whose kind (doc_id, record_kind) picks the mapping; documents of other kinds give nothing.

    The nodes meet their kinds once; an entity that several branches fill is the union of theirs.
    """
    marked = _cut(nodes.join(kinds, "doc_id"))
    out: dict[str, DataFrame] = {}
    for kind, mapping in branches.items():
        for entity, df in extract_entities(marked.filter(F.col("record_kind") == kind).drop("record_kind"), mapping, target).items():
            out[entity] = out[entity].unionByName(df) if entity in out else df
    return out


def occurrences(nodes: DataFrame, path: str) -> DataFrame:
    """All hits of a repetitive field's path, numbered in document order."""
    expr = compile_path(path)
    hits = nodes.withColumn("_path", path_text("plain")).filter(expr.matches(F.col("_path")))
    out = hits.withColumn("occurrence", F.row_number().over(Window.partitionBy("doc_id").orderBy("ord")))
    out = out if expr.index is None else out.filter(F.col("occurrence") == expr.index)
    return out.select("doc_id", "source", "occurrence", F.col("text").alias("value"))


def first_hit(nodes: DataFrame, paths: list[str]) -> DataFrame:
    """(doc_id, value): the first alternative that occurs in a document wins; of several hits the first."""
    p = path_text("plain")
    prio = reduce(lambda acc, kx: acc.when(compile_path(kx[1]).matches(p), kx[0]), list(enumerate(paths))[1:], F.when(compile_path(paths[0]).matches(p), 0))
    return nodes.withColumn("_k", prio).filter("_k is not null").groupBy("doc_id").agg(F.min(F.struct("_k", "ord", "text"))["text"].alias("value"))


def typed(entity: DataFrame, fields: dict[str, str], lang: str = "lang") -> tuple[DataFrame, DataFrame]:
    """(typed layer, rejects): text fields cast by the target's types; what does not cast is reported, not lost."""
    cast = {"text": lambda c: F.col(c), "date": lambda c: to_date_any(c), "boolean": lambda c: to_bool(c, lang), "integer": lambda c: F.col(c).try_cast("long"), "number": lambda c: F.col(c).try_cast("double"), "money": lambda c: F.col(c).try_cast("decimal(18,2)"), "link": lambda c: F.col(c)}
    good = entity.withColumns({c: cast[t](c) for c, t in fields.items()})
    bad = [F.when(F.col(c).isNotNull() & cast[t](c).isNull(), F.struct(F.lit(c).alias("field"), F.col(c).alias("value"))) for c, t in fields.items() if t != "text"]
    rejects = entity.select("id", F.explode(F.filter(F.array(*bad), lambda x: x.isNotNull())).alias("r")).select("id", "r.*") if bad else entity.select("id", F.lit("").alias("field"), F.lit("").alias("value")).limit(0)
    return good, rejects


def type_mismatches(entities: dict[str, DataFrame], target: Target) -> DataFrame:
    """(entity, field, type, bad, total): non-null values that don't cast to the target's type, for fields that have such values."""
    parts = []
    for name, df in entities.items():
        fields = {f: t for f, t in target.entities[name].fields.items() if t != "text" and f in df.columns}
        if not fields:
            continue
        good, _ = typed(df.withColumns({f"{f} as text": F.col(f) for f in fields}), fields)
        counts = good.agg(*[F.count(F.when(F.col(f"`{f} as text`").isNotNull() & F.col(f).isNull(), 1)).alias(f"{f} bad") for f in fields], *[F.count(f"`{f} as text`").alias(f"{f} total") for f in fields])
        cells = F.array(*[F.struct(F.lit(name).alias("entity"), F.lit(f).alias("field"), F.lit(t).alias("type"), F.col(f"`{f} bad`").alias("bad"), F.col(f"`{f} total`").alias("total")) for f, t in fields.items()])
        parts.append(counts.select(F.inline(cells)).filter("bad > 0"))
    return reduce(DataFrame.unionByName, parts)


def profile_values(entity: DataFrame, name: str) -> DataFrame:
    """(shape, n, example): outlines of a field's observed values."""
    from ..functions.columns import value_shape

    return entity.filter(F.col(name).isNotNull()).groupBy(value_shape(name).alias("shape")).agg(F.count(F.lit(1)).alias("n"), F.min(name).alias("example"))


# ids


def dense_ids(df: DataFrame, start: int = 0) -> DataFrame:
    """Reserved blocks: each task gets a range off a shared counter, as large as its row count; rows are numbered inside.

    The numbered rows are cut off in the shared folder, so a lost executor can't deal the blocks anew.
    """
    place = ["".join((n, "_" * (n in df.columns))) for n in ("_p", "_i", "_first", "_n")]
    p, i, first, n = place
    local = _cut(df.withColumns({p: F.spark_partition_id(), i: F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))}))
    sizes = local.groupBy(p).agg(F.count(F.lit(1)).alias(n))
    before = F.sum(n).over(Window.orderBy(p).rowsBetween(Window.unboundedPreceding, -1))
    # one row for each task
    blocks = sizes.select(p, (F.coalesce(before, F.lit(0)) + start).alias(first))
    return local.join(F.broadcast(blocks), p).withColumn("block_id", F.col(first) + F.col(i)).drop(p, i, first)


def monotonic_ids(df: DataFrame) -> DataFrame:
    return df.withColumn("id", F.monotonically_increasing_id())


def check_unique(entity: DataFrame) -> DataFrame:
    """Ids that occur more than once."""
    return entity.groupBy("id").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")


def two_phase(child: DataFrame, parent: DataFrame, natural: list[str], column: str) -> DataFrame:
    """Pointers by natural key after both sides exist; unknown parents leave the pointer null."""
    return child.drop(column).join(parent.select(*natural, F.col("id").alias(column)), natural, "left")


# flush


def flush_order(links: dict[str, set[str]]) -> list[list[str]]:
    """Levels of entities, each depending only on earlier ones. A cycle is an error that names it."""
    left, levels = {k: set(v) for k, v in links.items()}, []
    for v in list(left.values()):
        for x in v:
            left.setdefault(x, set())
    while left:
        level = sorted(k for k, v in left.items() if not v)
        if not level:
            at, trail = sorted(left)[0], []
            while at not in trail:
                trail.append(at)
                at = sorted(left[at])[0]
            raise ValueError("cycle: " + " -> ".join([*trail[trail.index(at) :], at]))
        levels.append(level)
        for k in level:
            del left[k]
        for v in left.values():
            v.difference_update(level)
    return levels


def target_order(target: Target) -> list[list[str]]:
    return flush_order({n: {t for t in e.links.values() if t != n} for n, e in target.entities.items()})


def flush(entities: dict[str, DataFrame], order: list[list[str]], sink: Callable[[str, DataFrame], None], batch_rows: int | None = None, writers: int = 4) -> list[str]:
    """Hands the entities to a sink level by level; a level only starts when the one before is written.

    The entities of one level don't depend on each other and are written by several threads at once. With batch_rows an
    entity comes in pools of at most that many rows, one partition each, so that a sink writes one batch a task.
    """
    done = []
    for level in order:
        names = [n for n in level if n in entities]
        with ThreadPoolExecutor(max_workers=max(1, min(writers, len(names)))) as pool:
            list(pool.map(lambda n: sink(n, entities[n] if batch_rows is None else pooled(entities[n], batch_rows)), names))
        done += names
    return done


def pooled(rows: DataFrame, batch_rows: int) -> DataFrame:
    """The rows in partitions of at most batch_rows rows."""
    numbered = dense_ids(rows)
    pools = max(1, -(-numbered.count() // batch_rows))
    pool = F.floor(F.col("block_id") / batch_rows).cast("int")
    # each pool is a partition of its own: ranges are cut between pool numbers
    return numbered.withColumn("block_id", pool).repartitionByRange(pools, "block_id").drop("block_id")


def insert_cost(rows: DataFrame, batch_rows: int, method: str) -> DataFrame:
    """(method, rows, batches): statements that pools of batch_rows rows take, by the reserved numbers of the rows."""
    pooled = dense_ids(rows).groupBy(F.floor(F.col("block_id") / batch_rows).alias("pool")).agg(F.count(F.lit(1)).alias("n"))
    return pooled.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("rows"), F.count(F.lit(1)).alias("batches")).select(F.lit(method).alias("method"), "rows", "batches")


def orphans(entities: dict[str, DataFrame], target: Target) -> DataFrame:
    """(entity, fk, n): pointers without the instance they point to."""
    found = []
    for name, df in entities.items():
        for column, to in target.entities[name].links.items():
            lost = df.filter(F.col(column).isNotNull()).join(entities[to].select(F.col("id").alias(column)), column, "left_anti") if to in entities else df.filter(F.col(column).isNotNull())
            found.append(lost.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("entity"), F.lit(column).alias("fk"), "n"))
    return reduce(DataFrame.unionByName, found)


def expert_cycle(load: Callable[[Mapping], dict[str, DataFrame]], judge: Callable[[dict[str, DataFrame], Mapping], tuple[float, Mapping | None]], mapping: Mapping, accept: float = 1.0, max_rounds: int = 10) -> tuple[Mapping, list[tuple[int, float]]]:
    """Map, load, validate, remap until the reviewer accepts; returns the mapping and the history of rates."""
    history = []
    for k in range(max_rounds):
        rate, better = judge(load(mapping), mapping)
        history.append((k, rate))
        if rate >= accept or better is None:
            break
        mapping = better
    return mapping, history
