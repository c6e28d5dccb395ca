"""Secret scan: candidates by shape, false positives removed by a random forest trained on labelled findings.

Everything on the data's path is DataFrame functions: candidates are runs of a text between delimiters (white space,
quotes, brackets, commas, =, :, ?, &, @ and others), so that secrets in compact JSON, URLs and connection strings stand
alone. They are described by length, character transitions, coverage by the corpus's dictionary, path marks and
neighbouring words. The dictionary is the set of letter triples in the corpus's most frequent words (at most 26^3 of them,
counted over all documents), and how often each letter follows another in them. The labelled findings are made from the formats below by hashing row numbers, so training needs no file.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Length from which a run can be a secret, alone or where a value is assigned; words in the dictionary, findings, trees, depth.
SHORTEST, ASSIGNED, DICTIONARY, FINDINGS, TREES, DEPTH = 16, 8, 4096, 9000, 40, 9
LETTERS = "abcdefghijklmnopqrstuvwxyz"
# Words beside a secret, and beside what only looks like one.
NAMES = "token|secret|passw|pwd|api[_-]?key|apikey|auth|bearer|credential|private|access[_-]?key"
BENIGN = "commit|sha|md5|checksum|digest|etag|uuid|guid|build|version|revision|image|file|path|url|href|email|mail|card|phone|hash"
# Beginnings that providers give their keys.
PREFIXES = "AKIA|ASIA|ghp_|gho_|ghs_|github_pat_|sk_live_|sk-|xox[abp]-|AIza|glpat-|eyJ"
FEATURES = ("length", "transitions", "distinct", "digits", "uppers", "signs", "hex", "coverage", "slashes", "extension", "named", "benign", "assigned", "quoted", "prefixed", "dots", "runs", "at_sign", "pairs", "follows_at", "query")
#: A run of the signs that values have, without the delimiters between values; a full stop or dash at its end is none of it.
RUN = r"[A-Za-z0-9+/_.~$!#%^*-]{8,}={0,2}"
TAIL = r"[.!]+$"


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id, place (number of the word), before (two words), after, word, and what valued() adds, for every run that could be a secret."""
    text = F.split(F.coalesce(F.col("text").cast("string"), F.lit("")), r"[ \t\n\r\f]+")
    long_words = F.filter(F.transform("words", lambda w, i: F.struct(i.alias("place"), w.alias("word"))), lambda s: (F.length(s["word"]) >= ASSIGNED) & s["word"].rlike(RUN))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("words")).select("doc_id", "words", F.explode(long_words).alias("c"))
    near = F.concat_ws(" ", F.slice("words", F.greatest(F.col("c.place") - 2, F.lit(0)) + 1, F.least(F.col("c.place"), F.lit(3))))
    after = F.coalesce(F.try_element_at("words", F.col("c.place") + 2), F.lit(""))
    found = rows.select("doc_id", F.col("c.place").alias("place"), near.alias("before"), after.alias("after"), F.col("c.word").alias("word"))
    return valued(found)


def valued(found: DataFrame) -> DataFrame:
    """One row for each run of a word: value, piece (its number), lead (what stands before it in the word, its end) and assigned.

    A value has SHORTEST or more characters with a digit among them, or ASSIGNED or more where something is assigned: after =
    or : in its word, or at the beginning of a word that follows one. A lead ends where the value begins; of a value that
    occurs twice in a word both have the lead of the first.
    """
    runs = F.transform(F.regexp_extract_all("word", F.lit(RUN), F.lit(0)), lambda x: F.regexp_replace(x, TAIL, ""))
    out = found.select("*", F.posexplode(runs).alias("piece", "value"))
    at = F.expr("instr(word, value)")
    lead = F.substr("word", F.greatest(at - 60, F.lit(1)), F.least(at - 1, F.lit(60)))
    out = out.withColumn("lead", lead)
    inside = F.col("lead").rlike("[=:][\"'`]*$") & ~F.col("lead").rlike("://$")
    begins = F.col("lead").rlike("^[\"'`(\\[{<]*$") & F.col("before").rlike("[=:]\\s*[\"'`]?$")
    out = out.withColumn("assigned", (inside | begins).cast("double"))
    n = F.length("value")
    return out.where(((n >= SHORTEST) & F.col("value").rlike("[0-9]")) | ((n >= ASSIGNED) & (F.col("assigned") > 0)))


def described(found: DataFrame, known: tuple[str, str]) -> DataFrame:
    """Adds the features; known: a string of 26^3 signs, 1 where the dictionary has that letter triple, and one of 26^2
    digits, the higher the oftener a letter follows another."""
    triples, pairs = known
    value, n = F.col("value"), F.length("value")
    upper = LETTERS.upper()
    shape = F.regexp_replace(F.translate(value, LETTERS + upper + "0123456789", "a" * 26 + "A" * 26 + "0" * 10), "[^aA0]", "-")
    share = lambda pattern: F.length(F.regexp_replace(value, pattern, "")) / n
    low = F.lower(value)
    code = lambda i: F.ascii(F.substr(low, i, F.lit(1))) - 97
    inside = lambda c: (c >= 0) & (c < 26)

    def covered(i: Column) -> Column:
        a, b, c = code(i), code(i + 1), code(i + 2)
        return F.when(inside(a) & inside(b) & inside(c) & (F.substr(F.lit(triples), a * 676 + b * 26 + c + 1, F.lit(1)) == "1"), 1.0).otherwise(0.0)

    def follows(i: Column) -> Column:
        a, b = code(i), code(i + 1)
        return F.when(inside(a) & inside(b), F.substr(F.lit(pairs), a * 26 + b + 1, F.lit(1)).cast("double")).otherwise(0.0)

    around = F.lower(F.concat_ws(" ", "before", "lead", "after"))
    context = F.lower(F.concat_ws(" ", "before", "lead"))
    features = {
        "length": n.cast("double"),
        "transitions": (F.length(F.regexp_replace(shape, r"(.)\1+", "$1")) - 1) / n,
        "distinct": F.size(F.array_distinct(F.split(value, ""))) / F.sqrt(n),
        "digits": share("[^0-9]"),
        "uppers": share("[^A-Z]"),
        "signs": share("[A-Za-z0-9]"),
        "hex": value.rlike("^[0-9a-fA-F]+$").cast("double"),
        "coverage": F.aggregate(F.sequence(F.lit(1), n - 2), F.lit(0.0), lambda s, i: s + covered(i)) / (n - 2),
        "slashes": share("[^/]"),
        "extension": value.rlike(r"[A-Za-z0-9]\.[A-Za-z]{1,5}$").cast("double"),
        "named": context.rlike(NAMES).cast("double"),
        "benign": context.rlike(BENIGN).cast("double"),
        "quoted": F.col("lead").rlike("[\"'`]$").cast("double"),
        "prefixed": value.rlike(f"^(?:{PREFIXES})").cast("double"),
        "dots": share("[^.]"),
        "runs": F.length(F.regexp_replace(value, r"(.)(?!\1\1)", "")) / n,
        "at_sign": around.contains("@").cast("double"),
        "pairs": F.aggregate(F.sequence(F.lit(1), n - 1), F.lit(0.0), lambda s, i: s + follows(i)) / (n - 1),
        "follows_at": F.col("lead").rlike("://[^/@:]*:$").cast("double"),
        "query": F.col("lead").rlike("[?&][A-Za-z0-9_-]{1,40}=$").cast("double"),
    }
    return found.withColumns(features)


def dictionary(docs: DataFrame, size: int = DICTIONARY) -> tuple[str, str]:
    """Letter triples and pairs of the most frequent words of 3 to 12 letters, counted over all documents (see described)."""
    words = docs.select(F.explode(F.split(F.lower(F.coalesce(F.col("text").cast("string"), F.lit(""))), "[^a-z]+")).alias("w")).where(F.length("w").between(3, 12))
    top = common.materialize(words.groupBy("w").count().orderBy(F.desc("count"), "w").limit(size), "dictionary")
    runs = lambda n: top.select(F.explode(F.transform(F.sequence(F.lit(1), F.length("w") - (n - 1)), lambda i: F.substr("w", i, F.lit(n)))).alias("t"))
    have = {r["t"] for r in runs(3).distinct().collect()}
    often = {r["t"]: r["count"] for r in runs(2).groupBy("t").count().collect()}
    most = max(often.values(), default=1)
    level = lambda n: min(9, int(10 * math.log1p(n) / math.log1p(most)))
    return "".join("1" if a + b + c in have else "0" for a in LETTERS for b in LETTERS for c in LETTERS), "".join(str(level(often.get(a + b, 0))) for a in LETTERS for b in LETTERS)


def labelled_findings(spark: SparkSession, n: int = FINDINGS) -> DataFrame:
    """before, word, after, label: secrets of several formats, and things of like shape that are none.

    The dictionary words among them are drawn as letter triples are in most languages: short syllables put together.
    """
    h = lambda salt: F.sha2(F.concat_ws(":", F.lit(salt), F.col("id").cast("string")), 256)
    pick = lambda salt, items: F.element_at(F.array(*map(F.lit, items)), F.pmod(F.xxhash64(F.lit(salt), "id"), F.lit(len(items))).cast("int") + 1)
    number = lambda salt, low, high: F.pmod(F.xxhash64(F.lit(salt), "id"), F.lit(high - low + 1)).cast("int") + low
    base64 = F.translate(F.concat(F.base64(F.unhex(h("a"))), F.base64(F.unhex(h("b")))), "=", "")
    cut = lambda text, length: F.substr(text, F.lit(1), length)
    syllables = ("the", "ing", "tion", "er", "and", "an", "in", "ment", "que", "der", "lich", "ver", "con", "re", "ou", "es", "st", "ble")
    word = F.concat(*[pick(f"s{i}", syllables) for i in range(5)])
    key = pick("key", ("token", "api_key", "API-KEY", "secret", "password", "passwd", "auth_token", "access_key", "private_key", "client_secret"))
    mark = pick("mark", (" =", " :", "=", ":", " = "))
    assigned = F.concat(F.lit("for the "), key, mark)
    benign = pick("benign", ("commit", "sha256", "md5", "checksum", "digest", "etag", "build", "revision", "image hash"))
    plain = pick("plain", ("the and", "of this", "in our", "to be", "is on", "de la", "und der"))
    quote = lambda x: F.concat(F.lit('"'), x, F.lit('"'))
    none = F.lit("")
    kinds = [  # before, word, label
        (assigned, quote(cut(h("h"), F.lit(40))), 1),
        (assigned, cut(h("h"), pick("l", (32, 40, 64))), 1),
        (assigned, quote(cut(base64, number("n", 20, 44))), 1),
        (assigned, cut(base64, number("n", 18, 40)), 1),
        (plain, F.concat(pick("p", ("AKIA", "ASIA")), cut(F.upper(base64), F.lit(16))), 1),
        (plain, F.concat(pick("p", ("ghp_", "glpat-", "sk_live_", "xoxb-", "AIza")), cut(F.translate(base64, "+/", "xy"), number("n", 24, 36))), 1),
        (none, F.concat(key, F.lit("="), cut(base64, number("n", 20, 40))), 1),
        (plain, cut(base64, number("n", 32, 44)), 1),
        (benign, cut(h("h"), pick("l", (32, 40, 64))), 0),
        (F.concat(benign, F.lit(":")), quote(cut(h("h"), F.lit(40))), 0),
        (pick("u", ("uuid", "id:", "guid =", "request")), F.concat_ws("-", *[F.substr(h("u"), F.lit(a), F.lit(b)) for a, b in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]), 0),
        (pick("f", ("see", "file:", "in", "path =")), F.concat(F.lit("/"), word, F.lit("/lib/"), pick("w", syllables), number("v", 1, 99).cast("string"), F.lit("/"), word, pick("e", (".py", ".txt", ".json", ".so"))), 0),
        (plain, F.concat(word, number("y", 1990, 2030).cast("string"), pick("w", syllables)), 0),
        (assigned, F.concat(pick("x", ("your_", "my-", "example_")), key, pick("y", ("_here", "_goes_here_1", "-placeholder"))), 0),
        (assigned, quote(F.rpad(pick("x", ("x", "0", "*1", "1234567890", "abc123")), number("n", 16, 32), pick("x", ("x", "0", "*1", "1234567890", "abc123")))), 0),
        (plain, cut(F.conv(cut(h("d"), F.lit(15)), 16, 10), number("n", 16, 17)), 0),
        (pick("u", ("card", "account", "no.", "of")), cut(F.regexp_replace(F.concat(h("d"), h("e")), "[a-f]", ""), F.lit(16)), 0),
        (plain, F.concat(pick("s", syllables), F.lit("."), number("n", 10, 99).cast("string"), F.lit("@mail"), number("m", 0, 9).cast("string"), F.lit(".example.com")), 0),
        (plain, F.concat(F.lit("https://"), pick("w", syllables), F.lit(".example.com/"), word, F.lit("/"), number("n", 1, 9999).cast("string")), 0),
        (plain, F.concat(number("y", 1990, 2030).cast("string"), F.lit("-01-02T03:04:05."), number("n", 100000, 999999).cast("string")), 0),
        (assigned, word, 0),
        (plain, F.concat(word, F.lit("_"), word, number("n", 1, 9).cast("string")), 0),
        (none, F.concat(F.lit('{"id":'), number("i", 1, 99).cast("string"), F.lit(',"'), key, F.lit('":"'), cut(h("h"), pick("l", (24, 32, 40))), F.lit('"}')), 1),
        (plain, F.concat(F.lit("https://"), pick("w", syllables), F.lit(".example.com/v1?"), pick("k", ("token", "key", "api_key", "access_token")), F.lit("="), cut(base64, number("n", 20, 40)), F.lit("&a=1")), 1),
        (plain, F.concat(pick("c", ("postgres", "mysql", "mongodb", "amqp")), F.lit("://"), pick("w", syllables), F.lit(":"), cut(F.translate(base64, "+/", "xy"), number("n", 9, 20)), F.lit("@db.example.com/"), pick("v", syllables)), 1),
        (none, F.concat(pick("p", ("password=", "passwd:", "DB_PASSWORD=", "pwd=", "KEY2=", "secret:")), F.initcap(pick("w", syllables)), cut(h("h"), number("n", 4, 8)), pick("s", ("!", "$", "#", "%", "*")), cut(base64, number("m", 2, 6))), 1),
        (none, F.concat(F.lit('{"id":"'), F.concat_ws("-", *[F.substr(h("u"), F.lit(a), F.lit(b)) for a, b in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]), F.lit('","name":"'), word, F.lit('"}')), 0),
        (plain, F.concat(F.lit("https://"), pick("w", syllables), F.lit(".example.com/"), word, F.lit("?page="), number("n", 10000000, 99999999).cast("string"), F.lit("&ref="), word), 0),
        (none, F.concat(pick("p", ("version=", "build:", "date=", "count:", "path=", "name=", "title:", "lang=")), pick("v", ("2024-01-31", "1.22.333-45", "20240131", "123456789", "some/file.txt", "readme-first"))), 0),
        (none, F.concat(pick("p", ("name=", "title:", "user=", "path:")), word), 0),
    ]
    rows = spark.range(n).withColumn("kind", F.pmod("id", F.lit(len(kinds))))
    column = lambda part: reduce(lambda c, k: c.when(F.col("kind") == k[0], k[1][part] if part < 2 else F.lit(k[1][2])), enumerate(kinds), F.when(F.lit(False), None))
    return rows.select(column(0).alias("before"), column(1).alias("word"), plain.alias("after"), column(2).alias("label"))


def train(findings: DataFrame, known: tuple[str, str], trees: int = TREES, depth: int = DEPTH) -> RandomForestClassificationModel:
    """A forest over labelled findings (before, word, after, label)."""
    rows = described(valued(findings), known)
    ready = VectorAssembler(inputCols=list(FEATURES), outputCol="features", handleInvalid="keep").transform(rows.withColumn("label", F.col("label").cast("double"))).select("features", "label")
    return RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=17, featureSubsetStrategy="onethird").fit(common.materialize(ready, "findings"))


def secrets(docs: DataFrame, findings: DataFrame | None = None, at_least: float = 0.5) -> DataFrame:
    """doc_id, place, piece, value, score, predicted for every candidate; predicted 1: a secret, 0: a false positive.

    Null and empty texts have no candidates; values of any length are kept whole; repeated rows give repeated findings; an
    empty table gives no rows.
    """
    known = dictionary(docs)
    model = train(labelled_findings(docs.sparkSession) if findings is None else findings, known)
    rows = described(candidates(docs), known)
    ready = VectorAssembler(inputCols=list(FEATURES), outputCol="features", handleInvalid="keep").transform(rows)
    score = vector_to_array(F.col("probability"))[1]
    return model.transform(ready).select("doc_id", "place", "piece", "value", score.alias("score"), (score >= at_least).cast("int").alias("predicted"))


def op3_secret_findings(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets(common.read(spark, sf_dir, "documents"))
    return found.select("doc_id", "place", "piece", F.length("value").alias("length"), F.sha2("value", 256).alias("value_sha256"), "score", "predicted")
