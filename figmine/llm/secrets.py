"""Secret scan: candidate strings, and a random forest that removes the false positives. DataFrame functions only.

Candidates are unbroken runs that mix digits with letters, with dots between their parts, and values assigned to a name
that ends like a secret's; both are taken to their end, however long. Each is described
by its length, the transitions between characters (pairs usual in words, changes of kind, case and sound), how much of it
dictionary words cover, whether it looks like a path, and the words on both sides of it. The forest is grown by Spark ML
from labelled findings (a table of context, candidate and label; ``quality`` measures it on findings held out; ``labelled_findings`` makes a default one) and then written out as one column expression, so scoring is part of
the scan's own stage: no join, no shuffle, no row leaves the JVM.

Nulls and edge cases: a null or empty text has no candidates; texts are read whole, whatever their length; repeated
rows are scanned each; a null id is kept; extra columns pass through (one named ``findings`` is replaced by the result),
and redaction returns the columns it was given, whatever their names.
"""

from __future__ import annotations

import re

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import free_names

#: Rows of labelled findings the forest is fitted on, at most.
TRAIN_ROWS = 6_000

_NAME = r"(?i:password|passwd|secret|token|api[_\-]?key|access[_\-]?key|auth)"
_SET = r"\s{0,3}[=:]\s{0,3}[\"']?"
# a dot belongs to a run only between two of its characters; possessive, so that the length costs no stack
_RUN = r"[A-Za-z0-9+/=_\-]"
CANDIDATE = (
    r"(?<![A-Za-z0-9+/=_\-.@])(?:"
    rf"[A-Za-z0-9_.\-]*{_NAME}{_SET}[^\s\"',;]{{6,}}+"
    rf"|(?=[A-Za-z+/=_\-.]*+[0-9])(?=[0-9+/=_\-.]*+[A-Za-z])(?=(?:{_RUN}|\.(?={_RUN})){{12}}){_RUN}++(?:\.{_RUN}++)*+"
    r")"
)
#: A cheap test that passes over texts without any candidate.
_GATE = _NAME + r"\s{0,3}[=:]|[0-9][+/=_\-.]*+[A-Za-z]|[A-Za-z][+/=_\-.]*+[0-9]"
_ASSIGNED = rf"^[A-Za-z0-9_.\-]*{_NAME}{_SET}"

_NEAR_SECRET = r"(?i)(?<![A-Za-z0-9])(password|passwd|secret|token|api.?key|access.?key|credential|auth|bearer|private)(?![A-Za-z0-9])"
_AFTER_HARMLESS = r"(?i)^[\s\"')\]]{0,3}(?:bytes?|lines?|pages?|rows?|items?|files?|times|commits?|releases?|degrees|km|mm|kg|%)(?![a-z])"
#: Pairs of letters that follow one another in words far more often than by chance.
_USUAL_PAIRS = "th|he|in|er|an|re|on|at|en|nd|ti|es|or|te|of|ed|is|it|al|ar|st|to|nt|ng|se|ha|as|ou|io|le|ve|co|me|de|hi|ri|ro|ic|ne|ea|ra|ce|li|ch|ll|be|ma|si|om|ur|qu|un|el|la|di|ei|ie"
_NEAR_HARMLESS = r"(?i)\b(commit|sha1|checksum|digest|uuid|version|build|index|href|src|file|path|image|isbn|example|page|figure)\b"

#: Words that cover much of harmless identifiers.
DICTIONARY = (
    "the and tion that with from this for have are not you all can her was one our out day get has him his how man new now old see two way who "
    "data file name user item list page index value test main home image config server client example sample default number section version build "
    "ing ed ly er est able ment ness der die und das ein sch keit ung les des une que mente los las del com net org html http www"
).split()


def _features(candidate, value, before, after):
    """Named numeric columns over a candidate, its bare value and the text on both sides."""
    n = F.greatest(F.length(value), F.lit(1)).cast("double")
    lower = F.lower(value)
    kinds = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(value, r"[^A-Za-z0-9]", "-"), "[a-z]", "a"), "[A-Z]", "A"), "[0-9]", "9")
    runs = F.regexp_replace(kinds, r"(.)\1+", "$1")
    letters = F.regexp_replace(lower, "[^a-z]", "")
    sounds = F.regexp_replace(F.regexp_replace(letters, "[aeiou]", "v"), "[^v]", "c")
    uncovered = F.regexp_replace(lower, "|".join(sorted(DICTIONARY, key=lambda w: (-len(w), w))), "")
    share = lambda pattern: (F.length(F.regexp_replace(value, pattern, "")) / n)
    return {
        "length": n,
        "class_changes": F.length(runs) / n,
        "digit_letter_changes": F.regexp_count(runs, F.lit("(?=(?:a9|9a|A9|9A))")) / n,
        "sound_changes": F.regexp_count(sounds, F.lit("(?=(?:vc|cv))")) / F.greatest(F.length(letters), F.lit(1)),
        "usual_pairs": F.regexp_count(lower, F.lit(f"(?=(?:{_USUAL_PAIRS}))")) / F.greatest(F.length(letters), F.lit(1)),
        "case_changes": F.regexp_count(runs, F.lit("(?=(?:aA|Aa))")) / n,
        "dictionary_cover": F.lit(1.0) - F.length(uncovered) / n,
        "digits": share("[^0-9]"),
        "upper": share("[^A-Z]"),
        "hex": share("[^0-9a-fA-F]"),
        "distinct": F.size(F.array_distinct(F.split(value, ""))) / n,
        "slashes": share("[^/]"),
        "dots_dashes": share(r"[^.\-_]"),
        "path": F.when(value.rlike(r"(?i)^(?:/|[a-z]+/)|\.(?:html?|js|css|png|jpe?g|py|java|txt|json|pdf)$|://"), 1.0).otherwise(0.0),
        "uuid": F.when(value.rlike(r"^[0-9a-fA-F]{8}-(?:[0-9a-fA-F]{4}-){3}[0-9a-fA-F]{12}$"), 1.0).otherwise(0.0),
        "known_prefix": F.when(value.rlike(r"^(?:AKIA|ASIA|ghp_|gho_|github_pat_|xox[abp]-|sk_live_|sk-|AIza|eyJ|glpat-)"), 1.0).otherwise(0.0),
        "assigned": F.when(candidate.rlike(_ASSIGNED), 1.0).otherwise(0.0),
        "near_secret": F.when(F.concat(before, candidate).rlike(_NEAR_SECRET), 1.0).otherwise(0.0),
        "near_harmless": F.when(before.rlike(_NEAR_HARMLESS), 1.0).otherwise(0.0),
        "after_harmless": F.when(after.rlike(_AFTER_HARMLESS), 1.0).otherwise(0.0),
        "closed": F.when(after.rlike("^[\"']"), 1.0).otherwise(0.0),
        "placeholder": F.when(lower.rlike(r"example|xxxx|your|change.?me|placeholder|dummy|<|>|\$\{|(.)\1{5}"), 1.0).otherwise(0.0),
    }


def bare(candidate):
    return F.regexp_replace(candidate, _ASSIGNED, "")


def labelled_findings(spark: SparkSession, rows: int = TRAIN_ROWS) -> DataFrame:
    """(before, candidate, after, label): findings of known outcome, drawn from forms of secrets and of look-alikes.

    Every value is a hash of its row number, so the table is the same on every run.
    """
    hexed = lambda salt: F.sha2(F.concat(F.col("id").cast("string"), F.lit(salt)), 256)
    mixed = lambda salt: F.regexp_replace(F.base64(F.unhex(hexed(salt))), "[=]", "")
    safe = lambda salt: F.translate(mixed(salt), "+/", "-_")
    upper = lambda salt, n: F.upper(F.substring(F.regexp_replace(mixed(salt), "[^A-Za-z2-7]", "Q"), 1, n))
    number = lambda salt: F.conv(F.substring(hexed(salt), 1, 13), 16, 10)
    pick = lambda salt, words: F.element_at(F.array(*[F.lit(w) for w in words]), (F.crc32(F.concat(F.col("id").cast("string"), F.lit(salt)).cast("binary")) % len(words) + 1).cast("int"))
    prose = pick("p", ["the value is ", "shown here ", "and then ", "of them, ", "en la ", "und die ", "dans le ", ""])
    harmless = pick("h", ["commit ", "sha1 checksum ", "digest: ", "uuid ", "version ", "build ", "index file ", "page image ", "see path "])
    word = lambda salt: F.concat(*[pick(f"{salt}{k}", DICTIONARY) for k in range(4)])
    forms = [
        (1, prose, F.concat(pick("k", ['token = "', "token: ", "secret=", "api_key = '", "auth: "]), F.substring(hexed("a"), 1, 40))),
        (1, prose, F.concat(pick("w", ["password=", "passwd: ", "PASSWORD = "]), F.substring(hexed("b"), 1, 18))),
        (1, prose, F.concat(F.lit("AKIA"), upper("c", 16))),
        (1, prose, F.concat(F.lit("ghp_"), F.substring(F.regexp_replace(mixed("d"), "[+/]", "x"), 1, 36))),
        (1, F.lit("secret key "), F.substring(mixed("e"), 1, 40)),
        (1, prose, F.concat(F.lit("sk_live_"), F.substring(hexed("f"), 1, 24))),
        (1, prose, F.concat(F.upper(F.lit('token = "')), F.upper(F.substring(hexed("g"), 1, 40)))),
        (1, prose, F.concat(F.lit("AIza"), F.substring(F.regexp_replace(mixed("i"), "[+/]", "_"), 1, 35))),
        (1, prose, F.concat(pick("v", ["DB_PASSWORD = ", "client_secret: ", "AWS_SECRET_ACCESS_KEY=", "my-app.auth: ", "x_api_key="]), F.substring(safe("v"), 1, 40))),
        (1, prose, F.concat(pick("x", ["DB_PASSWORD = ", "client_secret: ", "user.passwd=", "ACCESS_TOKEN: "]), F.substring(safe("x"), 1, 8))),
        (1, prose, F.concat(pick("y", ["DB_PASSWORD = ", "password=", "client_secret: "]), pick("ya", DICTIONARY), pick("yb", DICTIONARY), F.substring(number("y"), 1, 2), F.substring(hexed("yc"), 1, 1))),
        (1, prose, F.concat(F.lit("eyJ"), F.substring(safe("z"), 1, 17), F.lit(".eyJ"), F.substring(safe("za"), 1, 40), F.lit("."), F.substring(safe("zb"), 1, 43))),
        (1, prose, F.concat(pick("aa", ["token = ", "SERVICE_SECRET=", "secret: "]), hexed("ab"), safe("ac"), hexed("ad"), safe("ae"))),
        (0, prose, F.concat(F.lit("www."), word("af"), F.lit(".org/"), word("ag"), F.substring(number("ag"), 1, 2))),
        (0, prose, F.concat(word("ah"), F.lit("."), word("ai"), F.substring(number("ai"), 1, 2))),
        (0, prose, F.concat(F.lit("lib"), pick("aj", DICTIONARY), F.lit("-"), F.substring(number("aj"), 1, 1), F.lit("."), F.substring(number("ak"), 1, 2), F.lit(".tar.gz"))),
        (0, harmless, F.substring(hexed("j"), 1, 40)),
        (0, prose, F.concat_ws("-", F.substring(hexed("l"), 1, 8), F.substring(hexed("l"), 9, 4), F.substring(hexed("l"), 13, 4), F.substring(hexed("l"), 17, 4), F.substring(hexed("l"), 21, 12))),
        (0, prose, F.concat(word("m"), F.substring(number("m"), 1, 2))),
        (0, prose, F.concat(word("n"), F.lit("/"), word("o"), F.lit("-"), F.substring(number("n"), 1, 3))),
        (0, prose, F.concat(F.lit("figure-"), F.substring(number("q"), 1, 4), F.lit("-"), word("q"))),
        (0, prose, F.concat(pick("r", ["password=", "token = ", "secret: ", "api_key="]), pick("s", ["your-password", "changeme123", "xxxxxxxxxxxx", "example-token-1", "${PASSWORD}", "<password>", "dummydummy1"]))),
        (0, harmless, F.substring(hexed("t"), 1, 32)),
        (0, prose, F.concat(F.lit("AKIA"), F.lit("IOSFODNN7EXAMPLE"))),
        (0, prose, F.concat(pick("u", ["token: ", "secret=", "password: "]), word("u"))),
    ]
    kind = F.col("id") % len(forms)
    ends = {1: pick("e1", ["", '"', "'", "\n", " and then", ". The"]), 0: pick("e0", ["", '"', " lines of it", " bytes", " pages", ". The", " in all", ")"])}
    chosen = lambda k: F.coalesce(*[F.when(kind == i, f[k] if k else F.lit(f[0])) for i, f in enumerate(forms)])
    return spark.range(rows).select(chosen(1).alias("before"), chosen(2).alias("candidate"), F.when(chosen(0) == 1, ends[1]).otherwise(ends[0]).alias("after"), chosen(0).cast("double").alias("label"))


class Forest:
    """Trees as nested tuples (feature, threshold, left, right), a leaf being its prediction."""

    def __init__(self, trees: list, names: list[str]):
        self.trees, self.names = trees, names

    @staticmethod
    def parse(text: str, names: list[str]) -> Forest:
        lines = [(len(line) - len(line.lstrip()), line.strip()) for line in text.split("\n") if line.strip()]
        trees, at = [], 0

        def node():
            nonlocal at
            line = lines[at][1]
            at += 1
            if m := re.match(r"Predict: ([\d.]+)", line):
                return float(m[1])
            m = re.match(r"If \(feature (\d+) <= ([-\d.Ee]+)\)", line)
            left = node()
            at += 1  # Else
            return (int(m[1]), float(m[2]), left, node())

        while at < len(lines):
            if lines[at][1].startswith("Tree "):
                at += 1
                trees.append(node())
            else:
                at += 1
        return Forest(trees, names)

    def score(self, features):
        """Share of the trees that vote for a secret, over a struct column of the features."""

        def walk(tree):
            if isinstance(tree, float):
                return F.lit(tree)
            return F.when(features[self.names[tree[0]]] <= tree[1], walk(tree[2])).otherwise(walk(tree[3]))

        total = F.lit(0.0)
        for tree in self.trees:
            total = total + walk(tree)
        return total / len(self.trees)


def _of_finding() -> dict:
    return _features(F.col("candidate"), bare(F.col("candidate")), F.coalesce("before", F.lit("")), F.coalesce("after", F.lit("")))


def quality(findings: DataFrame, forest: Forest, least: float = 0.5) -> DataFrame:
    """One row: precision and recall of the forest over labelled findings; null where nothing is counted."""
    score = forest.score(F.struct(*[x.cast("double").alias(n) for n, x in _of_finding().items()]))
    said, true = score >= least, F.col("label") == 1
    both = F.count_if(said & true)
    return findings.where("candidate IS NOT NULL AND label IS NOT NULL").agg(
        F.try_divide(both, F.count_if(said)).alias("precision"), F.try_divide(both, F.count_if(true)).alias("recall"), F.count("*").alias("findings")
    )


def train(findings: DataFrame, trees: int = 15, depth: int = 5, train_rows: int = TRAIN_ROWS, seed: int = 7) -> Forest:
    """A forest from labelled findings (before, candidate, after, label); at most ``train_rows`` of them."""
    rows = findings.where("candidate IS NOT NULL AND label IS NOT NULL").limit(train_rows)
    features = _of_finding()
    table = rows.select(F.col("label").cast("double").alias("label"), *[c.cast("double").alias(n) for n, c in features.items()])
    table = VectorAssembler(inputCols=list(features), outputCol="features").transform(table).select("label", "features").coalesce(1)
    model = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="sqrt").fit(table)
    return Forest.parse(model.toDebugString, list(features))


def find_secrets(docs: DataFrame, forest: Forest, text: str = "text", least: float = 0.5, around: int = 32, into: str = "findings") -> DataFrame:
    """``docs`` with ``findings``: array of (start, candidate, value, score, is_secret), start from 1; every candidate is
    listed. A given column of that name is replaced."""
    docs = docs.drop(into) if into.lower() != text.lower() else docs
    matched, parts, located = free_names(docs, "matched", "parts", "located")
    body = F.coalesce(F.col(text), F.lit(""))
    matches = F.regexp_extract_all(body, F.lit(CANDIDATE), F.lit(0))
    pieces = F.split(body, CANDIDATE, -1)
    kind = "array<struct<start:int,candidate:string,before:string,after:string>>"
    state = F.struct(F.lit(1).alias("at"), F.array().cast(kind).alias("seen"))

    def step(acc, i):
        gap, m = F.get(F.col(parts), i), F.get(F.col(matched), i)
        start = acc["at"] + F.length(gap)
        one = F.struct(start.alias("start"), m.alias("candidate"), F.substring(gap, -around, around).alias("before"), F.substring(F.get(F.col(parts), i + 1), 1, around).alias("after"))
        return F.struct((start + F.length(m)).alias("at"), F.concat(acc["seen"], F.array(one)).alias("seen"))

    def describe(c):
        value = bare(c["candidate"])
        return F.struct(c["start"].alias("start"), c["candidate"].alias("candidate"), value.alias("value"), F.struct(*[x.cast("double").alias(n) for n, x in _features(c["candidate"], value, c["before"], c["after"]).items()]).alias("f"))

    def judge(c):
        score = forest.score(c["f"])
        return F.struct(c["start"].alias("start"), c["candidate"].alias("candidate"), c["value"].alias("value"), F.round(score, 6).alias("score"), (score >= least).alias("is_secret"))

    found = F.when(F.size(matched) > 0, F.aggregate(F.sequence(F.lit(0), F.size(matched) - 1), state, step, lambda s: s["seen"])).otherwise(F.array().cast(kind))
    gated = body.rlike(_GATE)
    return (
        docs.withColumn(matched, F.when(gated, matches))
        .withColumn(parts, F.when(F.size(matched) > 0, pieces))
        .withColumn(located, found)
        .withColumn(into, F.transform(F.transform(located, describe), judge))
        .drop(matched, parts, located)
    )


def redact_secrets(docs: DataFrame, forest: Forest | None = None, mark: str = "[SECRET]") -> DataFrame:
    """``docs`` with the value of every secret replaced by ``mark`` where it was found; every document stays, columns as
    they were. The same characters elsewhere are not touched, and no finding changes the place of another."""
    forest = forest or train(labelled_findings(docs.sparkSession))
    (into,) = free_names(docs, "findings")
    hit = F.filter(into, lambda f: f["is_secret"])

    def step(acc, f):
        # a value is the end of its candidate
        start = f["start"] + F.length(f["candidate"]) - F.length(f["value"])
        return F.struct(F.concat(acc["out"], F.col("text").substr(acc["at"], start - acc["at"]), F.lit(mark)).alias("out"), (start + F.length(f["value"])).alias("at"))

    state = F.struct(F.lit("").alias("out"), F.lit(1).alias("at"))
    cleaned = F.aggregate(hit, state, step, lambda acc: F.concat(acc["out"], F.col("text").substr(acc["at"], F.length("text"))))
    found = find_secrets(docs, forest, into=into)
    return found.withColumn("text", F.when(F.size(hit) > 0, cleaned).otherwise(F.col("text"))).select(*(F.col(f"`{c}`") for c in docs.columns))


def op1_random_forest_secrets(spark, sf_dir: str) -> DataFrame:
    forest = train(labelled_findings(spark))
    found = find_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"), forest)
    return found.select("doc_id", F.explode(F.filter("findings", lambda f: f["is_secret"])).alias("f")).select("doc_id", F.col("f.start").alias("start"), F.col("f.candidate").alias("candidate"), F.col("f.score").alias("score"))
