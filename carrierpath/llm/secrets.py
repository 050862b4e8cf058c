"""Secret scan: candidate strings judged by a random forest.

Candidates are unbroken strings of at least ``SHORTEST`` letters, digits and a few signs, and values of at least ``ASSIGNED``
characters of any kind but white space and quotes that are assigned to a name with a secret word in it. Each gets
features of its length, its character transitions, the share that dictionary words cover, the path-like
or URL-like look of it, and the neighbouring words. A random forest trained from labelled
findings removes false positives such as hashes in paths, identifiers, placeholders and long words.
A shorter string that nothing is assigned by is no candidate.

The forest of the registered query is trained on :func:`labelled_findings`, at most ``TRAIN_ROWS`` invented
findings; train your own from any table of (before, candidate, after, path, label).

Everything on the main path is DataFrame expressions and the JVM's forest. Null texts count
as empty, texts without candidates give no findings, repeated rows and repeated
candidates are judged each for themselves, texts of any length are searched whole,
and a null path counts as none.
"""

from __future__ import annotations

import base64
import hashlib
import random

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import text_of

#: Labelled findings that the forest is trained on, its trees and their depth.
TRAIN_ROWS, TREES, DEPTH = 4000, 20, 8
#: Findings with at least this probability are reported.
THRESHOLD = 0.5
#: Shortest candidate, shortest one that is assigned to a secret's name, and characters of context on either side.
SHORTEST, ASSIGNED, AROUND = 16, 8, 40

# Words that name a secret, words that name something else, and common parts of identifiers.
SECRET_WORDS = ("token", "secret", "password", "passwd", "pwd", "apikey", "api_key", "api-key", "auth", "bearer", "credential", "private", "access_key", "client_secret", "signature")
OTHER_WORDS = ("sha1", "sha256", "md5", "commit", "checksum", "digest", "hash", "uuid", "guid", "version", "example", "placeholder", "integrity", "etag", "revision")
DICTIONARY = (
    "the", "and", "for", "user", "name", "test", "data", "file", "path", "http", "www", "com", "org", "get", "set", "config", "value", "key", "your", "example", "change", "this", "here", "module",
    "class", "package", "service", "manager", "handler", "factory", "index", "page", "image", "asset", "static", "public", "version", "license", "readme", "build", "script", "main", "color", "width", "style",
    "account", "action", "address", "admin", "after", "agent", "array", "base", "before", "block", "button", "cache", "client", "cloud", "code", "column", "command", "common", "component", "content",
    "context", "control", "count", "create", "current", "date", "default", "delete", "device", "display", "document", "domain", "download", "element", "email", "enable", "engine", "environment", "error", "event",
    "field", "filter", "first", "folder", "form", "format", "function", "general", "group", "header", "height", "home", "host", "input", "insert", "install", "instance", "interface", "internal", "item",
    "label", "language", "last", "layout", "level", "library", "link", "list", "local", "location", "login", "mail", "message", "method", "model", "network", "node", "number", "object", "option",
    "order", "output", "parameter", "parent", "parse", "password", "people", "photo", "plugin", "point", "port", "position", "post", "process", "product", "profile", "project", "property", "query", "random",
    "remote", "report", "request", "required", "resource", "response", "result", "return", "root", "search", "secret", "section", "select", "server", "session", "setting", "simple", "source", "start", "state",
    "status", "string", "system", "table", "target", "template", "text", "theme", "time", "title", "token", "type", "update", "upload", "view", "window", "word", "work", "world", "write",
)
#: Pairs of letters that stand in those words.
COMMON_PAIRS = tuple(sorted({w[i : i + 2] for w in DICTIONARY for i in range(len(w) - 1)}))

_UNIT = r"[A-Za-z0-9_+/=.\-]"
_NAMED = "|".join("auth(?!or)" if w == "auth" else w for w in SECRET_WORDS)
# A value begins after a name with a secret word and a sign of assignment; signs that end a sentence or a list do not end it.
_VALUE = rf"[^\s\"'`]{{{ASSIGNED - 1},}}[^\s\"'`.,;:)\]}}]"
_AFTER_NAME = r"(?<=[:=]\s{0,3}[\"'`]?)(?<=(?i:" + _NAMED + r")[A-Za-z0-9_]{0,16}[\"'`]?\s{0,3}[:=]{1,2}\s{0,3}[\"'`]?)"
_CANDIDATE = rf"(?:(?<=[\s\"'`:=]){_AFTER_NAME}{_VALUE}|(?<!{_UNIT}){_UNIT}{{{SHORTEST},}})"


def _share(text: Column, pattern: str) -> Column:
    return F.length(F.regexp_replace(text, pattern, "")) / F.length(text)


def features(rows: DataFrame) -> DataFrame:
    """Adds the feature columns to rows (before, candidate, after, path)."""
    c, low = F.col("candidate"), F.lower("candidate")
    near = F.lower(F.concat_ws(" ", "before", "after"))
    cls = F.translate(F.translate(F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "A" * 26), "abcdefghijklmnopqrstuvwxyz", "a" * 26), "0123456789", "0" * 10)
    steps = F.length(F.regexp_replace(cls, r"(.)(?=\1)", "")) / F.length(c)  # runs of one kind of character
    words = "|".join(sorted(DICTIONARY, key=lambda w: (-len(w), w)))
    rare = F.length(F.regexp_replace(low, r"[^qxzjkvw]", "")) / F.length(c)
    vowels = F.length(F.regexp_replace(low, r"[^aeiou]", "")) / F.length(c)
    distinct = F.size(F.array_distinct(F.split(c, ""))) / F.length(c)
    common = F.length(c) - F.length(F.regexp_replace(low, rf"(?=(?:{'|'.join(COMMON_PAIRS)}))[a-z]", ""))  # letters that begin a common pair
    one = lambda x: x.cast("double")
    made = {
        "f_length": F.length(c), "f_steps": steps, "f_pairs": common / F.length(c), "f_signs": 1 - _share(c, r"[^A-Za-z0-9_+/=.\-]"), "f_distinct": distinct, "f_rare": rare, "f_vowels": vowels,
        "f_hex": one(low.rlike(r"^[0-9a-f]+$")), "f_digits": 1 - _share(c, r"[0-9]"), "f_upper": 1 - _share(c, r"[A-Z]"), "f_lower": 1 - _share(c, r"[a-z]"),
        "f_dictionary": 1 - _share(low, words), "f_dots": 1 - _share(c, r"[.]"), "f_slashes": 1 - _share(c, r"/"), "f_dashes": 1 - _share(c, r"[-_]"),
        "f_uuid": one(low.rlike(r"^[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}$")), "f_repeat": one(low.rlike(r"(.)\1{5,}|(..+)\2{2,}")),
        "f_known": one(c.rlike(r"^(?:AKIA|ASIA|ghp_|gho_|glpat-|xox[bap]-|sk_live_|AIza|eyJ)")),
        "f_assigned": one(F.col("before").rlike(r"[:=]\s*[\"']?$")), "f_quoted": one(F.col("before").rlike(r"[\"'`]$") & F.col("after").rlike(r"^[\"'`]")),
        "f_secret_word": one(near.rlike(_NAMED)), "f_secret_before": one(F.lower("before").rlike(rf"(?:{_NAMED})[a-z0-9_]{{0,16}}[\"'`]?\s*[:=]*\s*[\"'`]?$")),
        "f_other_word": one(near.rlike("|".join(OTHER_WORDS))), "f_url": one(F.col("before").rlike(r"(?:://|www\.|@|href=.?)\S*$")),
        "f_path": one(F.lower(F.coalesce("path", F.lit(""))).rlike(r"test|example|fixture|sample|lock|min\.js")), "f_config": one(F.lower(F.coalesce("path", F.lit(""))).rlike(r"\.env|config|settings|secret|\.ya?ml|\.properties")),
    }
    return rows.withColumns({k: v.cast("double") for k, v in made.items()})


FEATURES = (
    "f_length", "f_steps", "f_pairs", "f_signs", "f_distinct", "f_rare", "f_vowels", "f_hex", "f_digits", "f_upper", "f_lower", "f_dictionary", "f_dots", "f_slashes", "f_dashes",
    "f_uuid", "f_repeat", "f_known", "f_assigned", "f_quoted", "f_secret_word", "f_secret_before", "f_other_word", "f_url", "f_path", "f_config",
)


def labelled_findings(n: int = TRAIN_ROWS, seed: int = 11) -> list[tuple[str, str, str, str, int]]:
    """Invented findings (before, candidate, after, path, label)."""
    rng = random.Random(seed)
    letters = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"

    def noise(k, alphabet=letters):
        return "".join(rng.choice(alphabet) for _ in range(k))

    def prose(k=6):
        return " ".join("".join(rng.choice("th on er an re in ti es or st en ou ng al le ch de la".split()) for _ in range(rng.randint(1, 4))) for _ in range(k))

    def word_chain(sep, k):
        return sep.join(rng.choice(DICTIONARY).title() if rng.random() < 0.3 else rng.choice(DICTIONARY) for _ in range(k))

    out = []
    for i in range(n):
        secret = i % 2
        path = rng.choice(["", "src/app.py", "config/settings.yml", ".env", "tests/test_x.py", "docs/readme.md", "package-lock.json"])
        begin, end = rng.choice([("", ""), ('"', '"'), ("'", "'")])
        if secret:
            name = rng.choice(SECRET_WORDS)
            name = rng.choice(["", "my_", "db_", "API_"]) + rng.choice([name, name.upper(), name.title()])
            before = prose(rng.randint(0, 6)) + " " + name + rng.choice([" = ", "=", ": ", " := ", " "]) + begin
            cand = rng.choice([
                noise(rng.randint(16, 64)), noise(40, "0123456789abcdef"), noise(32, "0123456789abcdef"), noise(64, "0123456789abcdef"), "AKIA" + noise(16, "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
                "ghp_" + noise(36), "sk_live_" + noise(24), base64.b64encode(noise(rng.randint(18, 45)).encode()).decode(), "eyJ" + noise(30) + "." + noise(40) + "." + noise(43),
            ])
            if rng.random() < 0.25:  # a password that a person chose or a program made, after its name
                before = prose(rng.randint(0, 4)) + " " + name + rng.choice([" = ", "=", ": ", " := "]) + begin
                word = rng.choice(DICTIONARY).title() if rng.random() < 0.5 else noise(3)
                cand = rng.choice([noise(rng.randint(8, 15)), noise(rng.randint(8, 20), letters + "!@#$%^&*?-_+"), word + noise(rng.randint(2, 6), "0123456789") + noise(rng.randint(2, 6), "!@#$%^&*?" + letters)])
                cand = cand.ljust(ASSIGNED, "7")
            elif rng.random() < 0.1:
                before = prose(3) + " " + begin
                cand = rng.choice(["AKIA" + noise(16, "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"), "ghp_" + noise(36), "sk_live_" + noise(24)])
        else:
            digest = hashlib.sha256(str(rng.random()).encode()).hexdigest()
            kind = rng.randrange(11)
            before = prose(rng.randint(0, 6)) + " " + begin
            if kind == 0:
                cand, before = digest[: rng.choice([32, 40, 64])], before + rng.choice(OTHER_WORDS) + rng.choice([": ", " = ", " "]) + begin
            elif kind == 1:
                cand = word_chain(rng.choice(["_", "-", ".", ""]), rng.randint(4, 8))
            elif kind == 2:
                cand, before = word_chain("/", rng.randint(3, 7)), before + rng.choice(["https://", "/", "./"])
            elif kind == 3:
                cand = f"{digest[:8]}-{digest[8:12]}-{digest[12:16]}-{digest[16:20]}-{digest[20:32]}"
            elif kind == 4:
                cand, before = rng.choice(["x" * rng.randint(16, 40), "your-" + rng.choice(["token", "secret", "key"]) + "-goes-here", "0" * 32, "changeme" * 3, "1234567890" * 3, "EXAMPLE_" + word_chain("_", 3).upper()]), before + rng.choice(SECRET_WORDS) + " = " + begin
            elif kind == 5:
                cand = prose(1).replace(" ", "") + noise(1, "aeiou") + prose(1) + "".join(prose(4).split())
                cand = cand.replace(" ", "")[:48].ljust(SHORTEST, "e")
            elif kind == 6:
                cand, before = rng.choice(["-" * 30, "=" * 40, "." * 20, "_" * 25, "-+" * 12]), prose(2) + " "
            elif kind == 7:
                cand, before = f"{prose(1)}.{rng.randint(1, 99)}.mail{rng.randint(1, 9)}.example.com".replace(" ", ""), before + "@"
            elif kind in (8, 9):  # a name is followed by something that is no secret
                name = rng.choice(SECRET_WORDS)
                before += rng.choice(["", "my_", "the "]) + rng.choice([name, name.title()]) + rng.choice([" = ", ": ", "="])
                word = rng.choice([w for w in DICTIONARY if len(w) > 4])
                cand = rng.choice([
                    word + rng.choice(DICTIONARY), word + "." + rng.choice(DICTIONARY), word + "()", rng.choice(["get", "read", "os.environ["]) + word.title() + "()", "${" + word.upper() + "}", "<your-" + word + ">",
                    "{{ " + word + " }}", "*" * rng.randint(8, 20), "x" * rng.randint(8, 15), "changeme", "(" + word + ")", word + "-" + rng.choice(DICTIONARY), "%" + word + "%", prose(1) + prose(1), "".join(prose(3).split())[:15],
                ]).replace(" ", "").ljust(ASSIGNED, "s")
            else:
                cand = ".".join(str(rng.randint(0, 999)) for _ in range(6)) + str(rng.randint(10**8, 10**9))
            if kind not in (8, 9):
                cand = cand.ljust(SHORTEST, "e")
        out.append((before[-AROUND:], cand, (end + " " + prose(3))[:AROUND], path, secret))
    return out


def train(findings: DataFrame, trees: int = TREES, depth: int = DEPTH, seed: int = 5) -> RandomForestClassificationModel:
    """A forest from labelled findings (before, candidate, after, path, label)."""
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="vector").transform(features(findings)).select("vector", F.col("label").cast("double").alias("label"))
    return RandomForestClassifier(featuresCol="vector", labelCol="label", numTrees=trees, maxDepth=depth, seed=seed).fit(rows)


def default_forest(spark: SparkSession) -> RandomForestClassificationModel:
    rows = spark.createDataFrame(labelled_findings(), "before string, candidate string, after string, path string, label int")
    return train(rows.coalesce(1))


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: Column | None = None) -> DataFrame:
    """(doc_id, number, before, candidate, after, path): every candidate with what stands around it."""
    text = text_of(text_col)
    # Before and after the candidate in groups of one match each; the split keeps what lies between matches.
    own = docs.select(F.col(id_col).alias("doc_id"), text.alias("text"), (path if path is not None else F.lit(None)).cast("string").alias("path"))
    own = own.where(F.col("text").rlike(_CANDIDATE))
    pairs = own.select("doc_id", "path", F.regexp_extract_all("text", F.lit(rf"({_CANDIDATE})"), F.lit(1)).alias("found"), F.split("text", _CANDIDATE).alias("between"))
    each = pairs.select("doc_id", "path", "between", F.posexplode("found").alias("number", "candidate"))
    around = lambda at: F.coalesce(F.get("between", at), F.lit(""))
    return each.select(
        "doc_id", "number", F.substring(F.concat(F.lit(" " * AROUND), around(F.col("number"))), -AROUND, AROUND).alias("before"), "candidate",
        F.substring(around(F.col("number") + 1), 1, AROUND).alias("after"), "path",
    )


def scan(docs: DataFrame, forest: RandomForestClassificationModel | None = None, threshold: float = THRESHOLD, **columns) -> DataFrame:
    """(doc_id, number, candidate, probability) of the candidates that the forest takes for secrets."""
    forest = forest or default_forest(docs.sparkSession)
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="vector").transform(features(candidates(docs, **columns)))
    judged = forest.setFeaturesCol("vector").transform(rows).withColumn("probability", vector_to_array("probability")[1])
    return judged.where(F.col("probability") >= threshold).select("doc_id", "number", "candidate", "probability")
