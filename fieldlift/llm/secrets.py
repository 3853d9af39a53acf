"""Secret scans: pattern candidates, filtered by a random forest, with DataFrame functions only.

Candidates are assignments to a telling name, private key heads and long runs of key-like characters with a digit.
Each place of a candidate gets features from its length, character classes and their transitions, dictionary
coverage, path signs and the words beside it. A random forest trained from labelled findings (generated here from a seed; own
findings can be given) votes on each; its trees become conditional expressions, so the scan is one narrow projection
without shuffle, whatever the skew of the documents.

Defined cases: null and empty texts have no candidates, score 0, and stay as they are; repeated rows give repeated results;
a value that occurs several times in a text is judged at each of its places, counts once with its best score and that place's
kind, and is replaced everywhere; texts are scanned whole; an empty table gives an empty result; extra columns pass through.
"""

from __future__ import annotations

import json
import random
import re

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.functions import array_to_vector
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import free_name

#: Candidate patterns.
NAMES = r"(?i:password|passwd|pwd|passphrase|secret|token|api[_-]?key|access[_-]?key|auth[_-]?key|private[_-]?key|client[_-]?secret)"
GIVEN = NAMES + r"""[A-Za-z0-9_]*+["']?\s{0,2}[=:]\s{0,2}["']?"""
VALUE = r"""[^\s"'<>,;]{6,}"""
ASSIGNED = GIVEN + VALUE
KEY_HEAD = r"-----BEGIN [A-Z ]{0,24}PRIVATE KEY-----"
RUN = r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*[0-9])[A-Za-z0-9+/_-]{16,}={0,2}(?![A-Za-z0-9+/_-])"
CANDIDATE = f"{ASSIGNED}|{KEY_HEAD}|{RUN}"
#: Prefixes of issued keys, words that stand for values, words beside harmless strings, common words.
ISSUED = r"^(?:AKIA|ASIA)[0-9A-Z]{16}$|^gh[pousr]_[A-Za-z0-9]{20,}|^sk[-_][A-Za-z0-9_-]{16,}|^xox[abprs]-|^AIza[0-9A-Za-z_-]{30,}|^eyJ[A-Za-z0-9_-]{16,}|^glpat-|-----BEGIN"
STANDS_FOR = r"(?i)change.?me|example|your|placeholder|dummy|sample|redacted|xxxx|\*\*\*|\$\{|\{\{|todo|none|null|1234567"
BESIDE = r"(?i)\b(?:commit|sha1?|sha256|md5|checksum|digest|hash|etag|uuid|guid|revision|version|build|isbn|order|invoice|ticket|phone|http|https|www|file|path|image|base64|doi|color)\W{0,4}$"
TELLING = r"(?i)(?:password|passwd|pwd|passphrase|secret|token|key|credential|auth)\w*\W{0,5}$"
COMMON = tuple("about above account admin after again another before below change class client company config content could data default document every example field file first form found from function general group have home image index info input into item level line link list local login main make many model module name need next node note number object order other page param part path people place point public read release report request result right sample search server service session simple some state string system table test text that their them then there these they this time title tree type under update user value version view water what when where which with word work world would write year your".split())
FEATURES = ("length", "digits", "uppers", "transitions", "coverage", "variety", "hex", "slashes", "issued", "stands_for", "beside", "telling", "breaks", "vowels")
#: Parameters of the forest.
TREES, DEPTH, SEED = 24, 5, 17


def share(text: Column, pattern: str) -> Column:
    return 1.0 - F.length(F.regexp_replace(text, pattern, "")) / F.greatest(F.length(text), F.lit(1))


def value_of(candidate: Column) -> Column:
    """The secret part: what is assigned, or the whole run."""
    assigned = F.regexp_extract(candidate, f"^{GIVEN}({VALUE})$", 1)
    return F.when(assigned != "", assigned).otherwise(candidate)


def feature_array(candidate: Column, before: Column, after: Column, words: tuple[str, ...] = COMMON) -> Column:
    value = value_of(candidate)
    beside = F.concat(before, F.substring(candidate, F.lit(1), F.length(candidate) - F.length(value)))
    n = F.greatest(F.length(value), F.lit(1))
    turns = F.regexp_count(value, F.lit(r"[A-Za-z](?=[0-9])|[0-9](?=[A-Za-z])|[a-z](?=[A-Z])"))
    flag = lambda c: F.when(c, 1.0).otherwise(0.0)
    return F.array(
        F.length(value).cast("double"),
        share(value, "[0-9]"),
        share(value, "[A-Z]"),
        turns / n,
        share(F.lower(value), "|".join(re.escape(w) for w in sorted(words, key=len, reverse=True))),
        F.size(F.array_distinct(F.split(value, ""))) / n,
        flag(value.rlike("^[0-9a-f]+$") | value.rlike("^[0-9A-F]+$")),
        share(value, r"[/\\.]"),
        flag(value.rlike(ISSUED)),
        flag(value.rlike(STANDS_FOR)),
        flag(beside.rlike(BESIDE) | after.rlike(r"^[./\\][A-Za-z0-9]")),
        flag(beside.rlike(TELLING)),
        share(value, "[-_]"),
        share(F.lower(value), "[aeiou]"),
    )


def labelled_findings(seed: int = SEED, each: int = 40) -> list[dict]:
    """Findings with labels: keys as they are issued and assigned, and strings that only look like them."""
    rnd = random.Random(seed)
    pick = lambda alphabet, n: "".join(rnd.choice(alphabet) for _ in range(n))
    upper, digits, hexa = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789", "0123456789abcdef"
    alnum = upper + upper.lower() + digits
    word = lambda: rnd.choice(COMMON)
    names = ["password", "token", "secret", "api_key", "passwd", "access_key", "client_secret"]
    assign = lambda name, v: rnd.choice([f"{name}={v}", f'{name} = "{v}', f"{name}: {v}", f"{name}='{v}"])
    plain = lambda: f"{word()} {word()} "
    true = [
        lambda: (plain(), "AKIA" + pick(upper + digits, 16)),
        lambda: (plain(), assign(rnd.choice(names), pick(hexa, rnd.choice([12, 16, 17, 18, 20, 24, 32, 40])))),
        lambda: (plain(), assign(rnd.choice(names), pick(alnum, rnd.randint(12, 44)))),
        lambda: (plain(), assign("password", pick(alnum + "!@#%^&", rnd.randint(9, 20)) + pick(digits, 2))),
        lambda: (plain(), "ghp_" + pick(alnum, 36)),
        lambda: (plain(), "sk-" + pick(alnum, 40)),
        lambda: (plain(), "-----BEGIN RSA PRIVATE KEY-----"),
        lambda: (plain(), pick(alnum + "+/", 40) + pick(digits, 2)),
        lambda: (plain() + rnd.choice(["key ", "secret ", "auth "]), pick(alnum, rnd.randint(24, 44)) + pick(digits, 2)),
    ]
    false = [
        lambda: (plain() + rnd.choice(["commit ", "sha1 ", "checksum: ", "md5 ", "etag: "]), pick(hexa, rnd.choice([32, 40, 64]))),
        lambda: (plain() + rnd.choice(["uuid ", "order ", "", "version "]), "-".join(pick(hexa, k) for k in (8, 4, 4, 4, 12))),
        lambda: (plain(), assign(rnd.choice(names), rnd.choice(["changeme", "your_password", "example123", "${TOKEN}", "xxxxxxxx", "placeholder", "{{secret}}", "********", "none-given"]))),
        lambda: (plain(), assign(rnd.choice(names), rnd.choice([word() + word(), word() + "_" + word(), word() + "." + word() + "()", word() + "-" + word() + "-" + word()]))),
        lambda: (plain(), "/".join(word() for _ in range(4)) + pick(digits, 1)),
        lambda: (plain(), "-".join(word() for _ in range(4)) + "-" + pick(digits, 2)),
        lambda: (plain(), "_".join(word() for _ in range(3)) + "_v" + pick(digits, 2)),
        lambda: (plain(), pick(digits, rnd.randint(16, 22))),
        lambda: (plain(), f"20{pick(digits, 2)}-0{pick('123456789', 1)}-1{pick(digits, 1)}-{pick(digits, 2)}-{pick(digits, 4)}"),
        lambda: (plain() + "https://", "/".join(word() for _ in range(3)) + "/" + pick(digits, 6)),
        lambda: (plain(), word().capitalize() + word().capitalize() + word().capitalize() + pick(digits, 1) + word().capitalize()),
    ]
    return [{"before": b, "candidate": c, "after": " " + word(), "label": y} for makers, y in ((true, 1), (false, 0)) for make in makers for b, c in (make() for _ in range(each))]


def findings_frame(spark: SparkSession, findings: list[dict]) -> DataFrame:
    schema = "array<struct<before:string,candidate:string,after:string,label:int>>"
    return spark.range(1).select(F.inline(F.from_json(F.lit(json.dumps(findings)), schema)))


def train(findings: DataFrame, trees: int = TREES, depth: int = DEPTH, words: tuple[str, ...] = COMMON) -> list[tuple]:
    """Fits the forest and returns its trees as nested (feature, limit, left, right) or a leaf's class."""
    rows = findings.select(F.col("label").cast("double").alias("label"), array_to_vector(feature_array(F.col("candidate"), F.col("before"), F.col("after"), words)).alias("features")).coalesce(1)
    model = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=SEED, featureSubsetStrategy="sqrt", minInstancesPerNode=2).fit(rows)
    found, lines = [], iter(model.toDebugString.splitlines())

    def node(line: str):
        line = line.strip()
        if line.startswith("Predict:"):
            return float(line.split()[1])
        m = re.match(r"If \(feature (\d+) <= (\S+)\)", line)
        left = node(next(lines))
        next(lines)  # its Else
        return int(m[1]), float(m[2]), left, node(next(lines))

    for line in lines:
        if re.match(r"\s*Tree \d+", line):
            found.append(node(next(lines)))
    return found


def vote(forest: list[tuple], x: Column) -> Column:
    """Share of trees that call a finding true."""

    def tree(t) -> Column:
        return F.lit(t) if isinstance(t, float) else F.when(x.getItem(t[0]) <= t[1], tree(t[2])).otherwise(tree(t[3]))

    total = tree(forest[0])
    for t in forest[1:]:
        total = total + tree(t)
    return total / len(forest)


def bound(value: Column, body) -> Column:
    """body(value) with value computed once; inside other lambdas it would be computed for each element."""
    return F.transform(F.array(value), body).getItem(0)


def heads(rows: Column) -> Column:
    """The first struct of each value in sorted structs."""
    return bound(F.array_sort(rows), lambda s: F.filter(s, lambda r, i: (i == 0) | (F.get(s, i - 1)["value"] != r["value"])))


def judge(text: Column, forest: list[tuple], words: tuple[str, ...] = COMMON) -> Column:
    """array<struct<value, kind, score>> of a text's distinct values, each with the best of its places, in order of first appearance."""
    places = F.struct(F.regexp_extract_all(text, F.lit(CANDIDATE), F.lit(0)).alias("found"), F.split(text, CANDIDATE, -1).alias("between"))

    def finding(s: Column, c: Column, i: Column) -> Column:
        part = lambda name, k: F.coalesce(F.get(s[name], i + k), F.lit(""))
        # a candidate has at least 10 characters, so three before and two after it cover the words beside it
        before = F.concat(part("found", -3), F.right(part("between", -2), F.lit(24)), part("found", -2), F.right(part("between", -1), F.lit(24)), part("found", -1), F.right(part("between", 0), F.lit(24)))
        after = F.concat(F.left(part("between", 1), F.lit(16)), part("found", 1), F.left(part("between", 2), F.lit(16)), part("found", 2))
        kind = F.when(c.rlike(ISSUED), "issued").when(c.rlike(f"^(?:{ASSIGNED})"), "assigned").otherwise("run")
        return F.struct(value_of(c).alias("value"), kind.alias("kind"), feature_array(c, F.right(before, F.lit(24)), F.left(after, F.lit(16)), words).alias("x"), i.alias("at"))

    found = bound(places, lambda s: F.transform(s["found"], lambda c, i: finding(s, c, i)))
    scored = F.transform(found, lambda f: F.struct(f["value"].alias("value"), f["kind"].alias("kind"), vote(forest, f["x"]).alias("score"), f["at"].alias("at")))

    def best(all_places: Column) -> Column:
        first = heads(F.transform(all_places, lambda f: F.struct(f["value"].alias("value"), f["at"].alias("at"))))
        top = heads(F.transform(all_places, lambda f: F.struct(f["value"].alias("value"), (-f["score"]).alias("s"), f["at"].alias("at"), f["kind"].alias("kind"))))
        once = F.array_sort(F.zip_with(first, top, lambda a, b: F.struct(a["at"].alias("at"), a["value"].alias("value"), b["kind"].alias("kind"), (-b["s"]).alias("score"))))
        return F.transform(once, lambda f: F.struct(f["value"].alias("value"), f["kind"].alias("kind"), f["score"].alias("score")))

    return F.when(text.rlike(CANDIDATE), bound(scored, best)).otherwise(F.array().cast("array<struct<value:string,kind:string,score:double>>"))


def scan(docs: DataFrame, findings: DataFrame | None = None, limit: float = 0.5, words: tuple[str, ...] = COMMON) -> DataFrame:
    """docs with _findings (all judged candidates), _secrets (those kept) and _clean (text with secrets replaced).

    findings (before, candidate, after, label) train the forest, words are the dictionary of its coverage feature.
    Where docs has a column of such a name, underscores follow the new one's.
    """
    found, secret, clean = (free_name(docs, c) for c in ("_findings", "_secrets", "_clean"))
    return judged_texts(docs.select("*", F.col("text").alias(clean)), clean, found, secret, findings, limit, words).select(*docs.columns, found, secret, clean)


def judged_texts(rows: DataFrame, text: str, found: str, secret: str, findings: DataFrame | None = None, limit: float = 0.5, words: tuple[str, ...] = COMMON) -> DataFrame:
    """rows with judged candidates and secrets of a text column, which loses its secrets."""
    spark = rows.sparkSession
    forest = train(findings if findings is not None else findings_frame(spark, labelled_findings()), words=words)
    judged = rows.withColumn(found, judge(F.coalesce(text, F.lit("")), forest, words))
    judged = judged.withColumn(secret, F.filter(found, lambda f: f["score"] > limit))
    # longer values first, so a value inside another doesn't break it up
    values = F.array_sort(F.array_distinct(F.transform(secret, lambda f: F.struct((-F.length(f["value"])).alias("n"), f["value"].alias("v")))))
    return judged.withColumn(text, F.when(F.size(secret) > 0, F.aggregate(values, F.col(text), lambda t, v: F.replace(t, v["v"], F.lit("[secret]")))).otherwise(F.col(text)))


def scan_digest(docs: DataFrame) -> DataFrame:
    """(doc_id, n_candidates, n_secrets, max_score, kinds, clean_sha256) of every document."""
    s = scan(docs.select("doc_id", "text"))
    return s.select(
        "doc_id",
        F.size("_findings").cast("long").alias("n_candidates"),
        F.size("_secrets").cast("long").alias("n_secrets"),
        F.coalesce(F.array_max(F.transform("_findings", lambda f: f["score"])), F.lit(0.0)).alias("max_score"),
        F.array_join(F.array_sort(F.array_distinct(F.transform("_secrets", lambda f: f["kind"]))), ",").alias("kinds"),
        F.sha2(F.coalesce("_clean", F.lit("")), 256).alias("clean_sha256"),
    )


def redact(docs: DataFrame) -> DataFrame:
    """docs with secrets in text replaced; columns unchanged. Rows travel in a struct, so no name can clash."""
    wrapped = docs.select(F.struct("*").alias("row"), F.col("text").alias("cleaned"))
    judged = judged_texts(wrapped, "cleaned", "found", "secret")
    return judged.select(F.col("row").withField("text", F.col("cleaned")).alias("row")).select("row.*")
