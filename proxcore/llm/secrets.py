"""Secret scans: candidates by pattern, false positives removed by a random forest.

A candidate is a private-key block, a run of 16 or more token characters with a digit or a known prefix, or a value of 8 or
more characters after a word such as token or password, quoted or not; none has a longest length. The forest sees its
length, character classes, the share of each transition between two classes, the shares that placeholder words and the
corpus's own words cover, whether it stands in a path or address, and the neighbouring words. It is trained on labelled
findings: a table with the columns of candidates() and a boolean `label`, or, where there is none, on labelled_findings(),
which writes TRAIN_ROWS findings of known kinds. All of it runs in Spark's own functions and its ML library.

Defined results: a null or empty text has no candidates; overlapping candidates are one, from left to right; a key block without an
end is none; two marks
from the private-use area that stand in a text count as replacement characters; repeated rows are each scanned; the
forest and its training rows are the same in each run.
"""

from __future__ import annotations

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Labelled findings that the forest is fitted on at most, its trees and their depth; the least probability of a secret.
TRAIN_ROWS, TREES, DEPTH, LEAST = 6000, 24, 7, 0.5
_OPEN, _CLOSE = "\ue000", "\ue001"
CANDIDATE = (
    # within a block, runs of up to four dashes; possessive, so that it is scanned once and without recursion
    r"-----BEGIN [A-Z ]{0,30}PRIVATE KEY-----[^\-\ue000\ue001]*+(?:-{1,4}(?!-)[^\-\ue000\ue001]*+)*+-----END [A-Z ]{0,30}PRIVATE KEY-----"
    r"|(?<![A-Za-z0-9+/_\-])(?=[A-Za-z+/_\-]*+[0-9]|AKIA|ASIA|gh[pousr]_|glpat-|xox[abp]-|sk_live_|eyJ|AIza)[A-Za-z0-9+/_\-]{16,}+={0,2}"
    r"|(?<=(?i:password|passwd|secret|token|api_key|apikey)[\"']? ?[:=] ?[\"']?)[^\"'\s\ue000\ue001]{8,}+"
)
#: Words of the corpus that the dictionary holds at most: those of four letters or more in most documents.
VOCABULARY = 4096
#: Words, fixed values: what placeholders, paths and identifiers are made of; what goes before a secret; what goes before other codes.
DICTIONARY = "example sample test dummy placeholder changeme your insert here fake null none default public user name admin path file home lib usr bin src data page index image http https www com org net html version build release order account number item group state value model layer block batch config local server client service module thread alpha beta gamma north south east west".split()
SECRET_WORDS = "token secret password passwd pwd api_key apikey access_key auth authorization bearer credential private_key client_secret signature".split()
OTHER_WORDS = "commit sha md5 checksum digest hash etag uuid guid revision build isbn doi card iban phone tel fax invoice order tracking serial trace version".split()
FEATURES = ["log_length", "digits", "uppers", "hexes", "others", "distinct", "repeats", "placeholder", "covered", "in_path", "assigned", "quoted", "secret_near", "other_near", "known_prefix"]
#: Classes of characters: lower and upper letters, digits, others; a feature for each transition between two.
CLASSES = {"a": "lower", "A": "upper", "0": "digit", "-": "other"}
FEATURES += [f"{CLASSES[x]}_{CLASSES[y]}" for x in CLASSES for y in CLASSES]


def candidates(docs: DataFrame, *columns: str, text: str = "text") -> DataFrame:
    """The given columns of docs with start, end (characters), value, left and right (neighbouring text) of each candidate."""
    clean = F.translate(F.coalesce(F.col(text), F.lit("")), _OPEN + _CLOSE, "\ufffd\ufffd")
    some = docs.select(*columns, clean.alias("__text")).where(F.col("__text").rlike(CANDIDATE))
    pieces = F.split(F.regexp_replace("__text", f"({CANDIDATE})", f"{_OPEN}$1{_CLOSE}"), _OPEN)
    part = "struct<start:bigint,value:string,left:string,right:string>"
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.lit("").alias("left"), F.array().cast(f"array<{part}>").alias("out"))

    def take(state: Column, piece: Column) -> Column:
        value, rest = F.substring_index(piece, _CLOSE, 1), F.substring_index(piece, _CLOSE, -1)
        marked = F.contains(piece, F.lit(_CLOSE))
        found = F.array(F.struct(state["at"].alias("start"), value.alias("value"), state["left"].alias("left"), F.substring(rest, 1, 24).alias("right")))
        return F.struct(
            (state["at"] + F.length(piece) - F.when(marked, 1).otherwise(0)).alias("at"),
            F.substring(rest, -48, 48).alias("left"),
            F.when(marked, F.concat(state["out"], found)).otherwise(state["out"]).alias("out"),
        )

    found = some.select(*columns, F.explode(F.aggregate(pieces, start, take, lambda s: s["out"])).alias("__c"))
    return found.select(*columns, F.col("__c.start").alias("start"), (F.col("__c.start") + F.length("__c.value")).alias("end"), F.col("__c.value").alias("value"), F.col("__c.left").alias("left"), F.col("__c.right").alias("right"))


def _near(words: list[str]) -> Column:
    return F.col("left").rlike(r"(?i)(?<![a-z])(?:" + "|".join(words) + r")s?(?![a-z])[^\n]{0,16}$").cast("double")


def vocabulary(docs: DataFrame, *, text: str = "text", most: int = VOCABULARY) -> list[str]:
    """The words [a-z]{4,} (lower-cased) that are in most of all documents, at least two; by name at ties."""
    words = docs.select(F.explode(F.array_distinct(F.split(F.lower(F.col(text)), "[^a-z]+"))).alias("word")).where("length(word) >= 4")
    counts = words.groupBy("word").agg(F.count("*").alias("n")).where("n > 1")
    return [r["word"] for r in counts.orderBy(F.desc("n"), "word").limit(most).collect()]  # at most `most` of them


def features(found: DataFrame, words: list[str] = ()) -> DataFrame:
    """found with the columns FEATURES; words is the corpus's vocabulary."""
    v, n = F.col("value"), F.greatest(F.length("value"), F.lit(1)).cast("double")
    share = lambda pattern: F.regexp_count(v, F.lit(pattern)) / n
    lower, upper, digits = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    kinds = F.regexp_replace(F.translate(v, lower + upper + digits, "a" * 26 + "A" * 26 + "0" * 10), "[^aA0]", "-")
    pairs = F.greatest(F.length("value") - 1, F.lit(1)).cast("double")
    listed = ", ".join(f"'{w}'" for w in [*words, *DICTIONARY])  # letters alone
    runs = "split(lower(regexp_replace(value, '([a-z])([A-Z])', '$1 $2')), '[^a-z]+')"
    known = F.expr(f"aggregate(filter({runs}, w -> w IN ({listed})), 0, (n, w) -> n + length(w))")
    return found.withColumns({f"{CLASSES[x]}_{CLASSES[y]}": F.regexp_count(kinds, F.lit(f"{x}(?={y})")) / pairs for x in CLASSES for y in CLASSES} | {
        "log_length": F.log(n),
        "digits": share("[0-9]"),
        "uppers": share("[A-Z]"),
        "hexes": share("[0-9a-fA-F]"),
        "others": share("[^0-9A-Za-z]"),
        "distinct": F.size(F.array_distinct(F.split(v, ""))) / n,
        "repeats": share(r"(.)(?=\1)"),
        "covered": known / n,
        "placeholder": 1 - F.length(F.regexp_replace(F.lower(v), "|".join(sorted(DICTIONARY, key=len, reverse=True)), "")) / n,
        "in_path": (F.col("left").rlike(r"[/\\.@]$|://[^\s]*$") | F.col("right").rlike(r"^[/\\.@]\w") | (share("/") > 0.04)).cast("double"),
        "assigned": F.col("left").rlike(r"[:=]>?\s{0,2}[\"'`]?$").cast("double"),
        "quoted": F.col("left").rlike("[\"'`]$").cast("double"),
        "secret_near": _near(SECRET_WORDS),
        "other_near": _near(OTHER_WORDS),
        "known_prefix": v.rlike(r"^(?:AKIA|ASIA|gh[pousr]_|glpat-|xox[abp]-|sk_live_|eyJ|AIza|-----BEGIN)").cast("double"),
    })


def labelled_findings(spark: SparkSession, rows: int = TRAIN_ROWS, salt: str = "train") -> DataFrame:
    """left, value, right, label: findings whose kind is known because they are written here, from hashes of row numbers."""
    h = lambda name: F.md5(F.concat(F.lit(f"{salt}:{name}:"), F.col("id").cast("string")))
    pick = lambda name, options: F.element_at(F.array(*[F.lit(x) if isinstance(x, str) else x for x in options]), (F.conv(F.substring(h(name), 1, 6), 16, 10).cast("bigint") % len(options) + 1).cast("int"))
    hexes = F.concat(h("a"), h("b"))
    code = F.translate(F.base64(F.unhex(F.concat(h("c"), h("d"), h("e")))), "+/=", "xyz")
    size = (F.conv(F.substring(h("n"), 1, 4), 16, 10).cast("bigint") % 25 + 20).cast("int")
    number = F.substring(F.translate(hexes, "abcdef", "012345"), 1, 16)
    word = lambda k: pick(f"w{k}", DICTIONARY)
    random_value = pick("random", [F.substring(hexes, 1, 40), F.substring(hexes, 1, 32), F.substring(hexes, 1, 64), F.upper(F.substring(hexes, 1, 40)), F.substring(code, F.lit(1), size), F.substring(code, F.lit(1), size)])
    known = pick("known", [F.concat(F.lit("AKIA"), F.upper(F.substring(F.translate(code, "0189", "QRST"), 1, 15)), F.lit("7")), F.concat(F.lit("ghp_"), F.substring(code, 1, 36)), F.concat(F.lit("sk_live_"), F.substring(code, 1, 24)), F.concat(F.lit("eyJ"), F.substring(code, 1, 40)), F.concat(F.lit("xoxb-"), number, F.lit("-"), F.substring(code, 1, 24))])
    plain = pick("plain", [
        F.concat(word(1), F.lit("_"), word(2), F.lit("_"), word(3), F.lit("_"), F.substring(number, 1, 2)), F.concat(word(1), F.lit("-"), word(2), F.lit("-2024-"), word(3)),
        F.concat(F.lit("your-"), word(1), F.lit("-token-here-1234")), F.repeat(F.substring(hexes, 1, 1), 24), F.lit("1234567890abcdef1234567890abcdef"),
        F.concat(word(1), F.lit("/"), word(2), F.lit("/v2/"), word(3), F.lit("/"), word(4)), number, F.concat(F.lit("xxxxxxxxxxxx"), F.substring(number, 1, 4)),
    ])
    uuid = F.concat_ws("-", F.substring(hexes, 1, 8), F.substring(hexes, 9, 4), F.substring(hexes, 13, 4), F.substring(hexes, 17, 4), F.substring(hexes, 21, 12))
    filler = pick("filler", ["of the and to ", "is here. Set ", "use this\n", "### ", "que de la ", "und der die ", ""])
    secret_left = F.concat(filler, pick("shift", [F.col("sw"), F.upper("sw"), F.concat(F.lit("my_"), F.col("sw"))]), pick("sep", [" = \"", "=", ": ", " = '", "=\"", "\": \"", " "]))
    other_left = F.concat(filler, pick("ow", OTHER_WORDS), pick("osep", [" ", ": ", "=", " = \"", ":"]))
    path_left = F.concat(filler, pick("path", ["https://www.example.com/", "/usr/lib/", "http://cdn.site.org/a/", "./build/", "C:\\data\\"]))
    kind = (F.conv(F.substring(h("kind"), 1, 4), 16, 10).cast("bigint") % 10).cast("int")
    left = F.when(kind < 3, secret_left).when(kind == 3, filler).when(kind == 4, pick("mixed", [filler, secret_left])).when(kind == 5, other_left).when(kind == 6, path_left).when(kind == 7, secret_left).otherwise(filler)
    value = F.when(kind < 3, random_value).when((kind == 3) | (kind == 4), known).when(kind == 5, pick("ov", [random_value, uuid, number])).when(kind == 6, pick("pv", [random_value, plain])).when(kind == 7, plain).otherwise(pick("lone", [plain, plain, number, uuid]))
    base = spark.range(rows).withColumn("sw", pick("sw", SECRET_WORDS))
    return base.select("id", left.alias("left"), value.alias("value"), pick("right", ["\"", "\" ", " ", "\n", ", ", "'"]).alias("right"), (kind < 5).cast("double").alias("label"))


def train(findings: DataFrame, words: list[str] = (), *, most_rows: int = TRAIN_ROWS) -> RandomForestClassificationModel:
    """A forest on at most most_rows labelled findings, the first by the hash of their text. words must be those of judge()."""
    some = features(findings.orderBy(F.xxhash64("left", "value", "right"), "left", "value", "right").limit(most_rows), words).withColumn("label", F.col("label").cast("double"))
    return RandomForestClassifier(numTrees=TREES, maxDepth=DEPTH, maxBins=32, seed=11, featuresCol="__features", labelCol="label", probabilityCol="__probability", rawPredictionCol="__raw", predictionCol="__prediction").fit(VectorAssembler(inputCols=FEATURES, outputCol="__features").transform(some))


def judge(found: DataFrame, model: RandomForestClassificationModel, words: list[str] = (), least: float = LEAST) -> DataFrame:
    """found with probability and is_secret."""
    scored = model.transform(VectorAssembler(inputCols=FEATURES, outputCol="__features").transform(features(found, words)))
    return scored.withColumn("probability", vector_to_array("__probability")[1]).drop("__features", "__probability", "__raw", "__prediction", *FEATURES).withColumn("is_secret", F.col("probability") >= least)


def redact(docs: DataFrame, model: RandomForestClassificationModel, words: list[str] = (), *, text: str = "text", least: float = LEAST, mark: str = "[SECRET]") -> DataFrame:
    """docs with confirmed secrets of the text replaced; only rows with candidates are shuffled, by the digest of their text."""
    has = F.coalesce(F.translate(F.col(text), _OPEN + _CLOSE, "\ufffd\ufffd").rlike(CANDIDATE), F.lit(False))
    some = docs.where(has).withColumn("__digest", F.md5(text))
    texts = some.groupBy(F.col("__digest")).agg(F.first(text).alias("__whole"))
    spans = judge(candidates(texts, "__digest", text="__whole"), model, words, least).where("is_secret").groupBy(F.col("__digest").alias("__of")).agg(F.sort_array(F.collect_set(F.struct("start", "end"))).alias("__spans"))
    joined = some.join(spans, F.col("__digest") == F.col("__of"), "left")
    zero = F.struct(F.lit(0).cast("bigint").alias("at"), F.lit("").alias("out"))
    cut = lambda a, b: F.substring(F.col(text), (a + 1).cast("int"), (b - a).cast("int"))
    fixed = F.aggregate("__spans", zero, lambda s, p: F.struct(p["end"].alias("at"), F.concat(s["out"], cut(s["at"], p["start"]), F.lit(mark)).alias("out")), lambda s: F.concat(s["out"], cut(s["at"], F.length(text).cast("bigint"))))
    changed = joined.withColumn(text, F.when(F.col("__spans").isNull(), F.col(text)).otherwise(fixed)).select(*docs.columns)
    return docs.where(~has).unionByName(changed)
