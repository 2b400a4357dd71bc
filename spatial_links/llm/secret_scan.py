"""Secret scans: candidate strings, then a random forest that removes false positives.

Candidates are strings of at least `MIN_LENGTH` key characters with a digit, of mixed case or after a known prefix of
keys, values assigned to a credential word (in any case, quoted or not), and private-key headers. The forest looks at length, character transitions, dictionary
coverage, the document's source path and the neighbouring words. It is fitted on labelled findings that
`labelled_findings` writes out of public key shapes and of the look-alikes that scanners trip over; their number is a
parameter. Fitting and scoring use DataFrame functions and spark.ml only. Scanning is one pass without a shuffle.

Null and empty texts have no candidates. Equal rows give equal findings; rows without a doc_id are scanned like others. The
number of candidates of a text is not capped, and the work grows in proportion to it. Extra columns of docs are ignored, or
kept by `redact` under whatever names; a missing source counts as empty.
"""

from __future__ import annotations

from functools import reduce
from zlib import crc32

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.llm.common import BROADCAST_IDS, materialise

MIN_LENGTH, NEAR, TRAINING_ROWS, TREES, DEPTH, THRESHOLD, SEED, WORDS_A_ROW = 16, 40, 4000, 24, 7, 0.5, 5, 24
_KEY = "A-Za-z0-9+/_-"
_CREDENTIAL = "password|passwd|secret|token|apikey|api_key"
#: How keys of well-known services begin.
_PREFIX = "AKIA|ASIA|gh[oprsu]_|github_pat_|glpat-|sk-|[rs]k_live_|xox[abprs]-|AIza"
#: One candidate: a key-like string, a string after a known prefix, a value assigned to a credential word, or a private key's header.
CANDIDATE = (
    rf"(?<![{_KEY}])(?=[A-Za-z+/_-]*+[0-9])[{_KEY}]{{{MIN_LENGTH},}}+={{0,2}}"
    rf"|(?<![{_KEY}])(?=[a-z]*+[A-Z]++[a-z]++[A-Z])[A-Za-z+/_-]{{20,}}+={{0,2}}"
    rf"|(?<![{_KEY}])(?:{_PREFIX})[{_KEY}]{{{MIN_LENGTH},}}+={{0,2}}"
    rf"|(?<=[:= \"'])(?<=(?i:{_CREDENTIAL})[\"']? {{0,2}}[:=] {{0,2}}[\"']?)[^\s\"']{{8,}}"
    r"|-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----"
)
#: Common words of made-up keys, of identifiers and of English, four letters or more.
DICTIONARY = tuple(
    "about access account action active address after again agent alert alpha always amount another answer apply archive around array author back base batch before begin beta "
    "block body book branch buffer build button cache call camera cent change chapter check city class clear client close cloud code color column come command comment commit "
    "common company config connect content control copy core count country create current data date debug default delete demo design detail device digit domain down draft drive dummy "
    "edit email enable engine entry error event every example export field figure file filter final find first folder font form format free from full function game gate graph green group hand "
    "handler header help here high home host hour house html http image import index info input insert issue item java jpeg json just kernel keep label language large last layer left "
    "letter level library light line link list load local lock login long loop main make manager market master match media member memory menu message method minute model module month more "
    "name network news next node note number object offset online open option order other output package page paper parent part password path payment people person phone photo place "
    "placeholder plan play please point port post price print private process product profile project proxy public query quick random read record release remote report request response result "
    "return review right role root route rule sample save scale schema score screen script search season second secret section select self send serial server service session shared shop show side sign "
    "simple site size small social some sort source space special stage start state station status step stone store story stream street string style submit support switch system table task team "
    "temp template test text than that their them theme then there this thread time title today token tool topic total town track travel tree type under unit update upload user valid value "
    "version video view water week well what when where which width will window with word work world would write xxxx year your yours zone 0000 1234 abcd changeme".split()
)
FEATURES = ("length", "digit_share", "upper_share", "lower_share", "hex", "transitions", "distinct_share", "longest_letters", "vowel_share", "dictionary_share", "test_path", "credential_near", "assigned", "quoted", "harmless_near", "header")


def _share(x: Column, kind: str) -> Column:
    return F.length(F.regexp_replace(x, kind, "")) / F.greatest(F.length(x), F.lit(1))


def features(df: DataFrame) -> DataFrame:
    """Adds FEATURES to rows with token, before, after, path."""
    t, low, before = F.col("token"), F.lower("token"), F.lower("before")
    kinds = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(t, "[a-z]+", "\u0001"), "[A-Z]+", "\u0002"), "[0-9]+", "\u0003"), "[^\u0001-\u0003]+", "\u0004")
    letters = F.array_max(F.transform(F.split(low, "[^a-z]+"), F.length))
    values = {
        "length": F.least(F.length(t), F.lit(200)),
        "digit_share": _share(t, "[^0-9]"),
        "upper_share": _share(t, "[^A-Z]"),
        "lower_share": _share(t, "[^a-z]"),
        "hex": t.rlike("^[0-9a-f]+$|^[0-9A-F]+$"),
        "transitions": F.length(kinds) / F.length(t),
        "distinct_share": F.size(F.array_distinct(F.split(t, ""))) / F.length(t),
        "longest_letters": letters,
        "vowel_share": _share(low, "[^aeiou]"),
        "dictionary_share": 1 - F.length(F.regexp_replace(low, "|".join(sorted(DICTIONARY, key=len, reverse=True)), "")) / F.length(t),
        "test_path": F.lower("path").rlike("test|example|sample|fixture|docs?/|readme"),
        "credential_near": before.rlike("passw|secret|token|api.?key|auth|bearer|credential|private|access.?key"),
        "assigned": before.rlike("[:=] ?[\"'`]?$"),
        "quoted": before.rlike("[\"'`]$") & F.col("after").rlike("^[\"'`]"),
        "harmless_near": before.rlike("commit|sha-?[0-9]|checksum|digest|md5|uuid|isbn|version|figure|image|page|src=|href="),
        "header": t.startswith("-----BEGIN"),
    }
    return df.select("*", *(F.coalesce(v.cast("double"), F.lit(0.0)).alias(k) for k, v in values.items()))


def _some_words(n: Column) -> Column:
    """WORDS_A_ROW words by hashes of a number: half of the dictionary, half made up of syllables."""
    of = lambda i, salt, xs: F.element_at(F.array(*(F.lit(x) for x in xs)), (F.pmod(F.xxhash64(n, i, F.lit(salt)), F.lit(len(xs))) + 1).cast("int"))
    syllable = lambda i, salt: F.concat(of(i, f"{salt}c", [*"bcdfghklmnprstvw", "br", "st", "tr", "ch", "gl", "th"]), of(i, f"{salt}v", [*"aeiou", "ai", "ou", "ea"]), of(i, f"{salt}e", ["", "", "n", "r", "s", "l", "nd", "ng"]))
    known = [w for w in DICTIONARY if w.isalpha()][::9]
    made_up = lambda i: F.concat(syllable(i, "1"), syllable(i, "2"), F.when(of(i, "more", [0, 1]) == 0, syllable(i, "3")).otherwise(""))
    return F.transform(F.sequence(F.lit(1), F.lit(WORDS_A_ROW)), lambda i: F.when(of(i, "kind", [0, 1]) == 0, of(i, "known", known)).otherwise(made_up(i)))


def labelled_findings(spark: SparkSession, rows: int = TRAINING_ROWS) -> DataFrame:
    """token, before, after, path, label: findings of known kinds, made of hashes of their number."""
    n = F.col("id")
    pick = lambda salt, *xs: F.element_at(F.array(*(F.lit(x) for x in xs)), (F.pmod(F.xxhash64(n, F.lit(salt)), F.lit(len(xs))) + 1).cast("int"))
    hex_ = lambda salt, size: F.substring(F.sha2(F.concat_ws("-", n, F.lit(salt)), 512), 1, size)
    b64 = lambda salt, size: F.substring(F.regexp_replace(F.base64(F.unhex(F.sha2(F.concat_ws("-", n, F.lit(salt)), 512))), "\n", ""), 1, size)
    word = lambda salt: F.get("words", F.lit(crc32(salt.encode()) % WORDS_A_ROW))
    glued = lambda salt, k: F.concat(*(word(f"{salt}{i}") for i in range(k)))
    near = pick("near", "token = \"", "api_key: ", "secret=", "password = '", "Authorization: Bearer ", "access_key = \"", "key: \"")
    given = pick("given", "PASSWORD=", "DB_SECRET=", "Password: ", '"password": "', '"token": "', "password = '", "secret=", '"api_key": "', "API_KEY = ")
    plain = pick("plain", "see the ", "in that ", "", "- ", "und der ", "of the ", "(", "les ")
    harmless = pick("harmless", "commit ", "sha256:", "md5 ", "checksum = ", "uuid: ", "image src=\"", "version ")
    close = lambda b: F.when(b.endswith('"'), '"').when(b.endswith("'"), "'").otherwise(" and")
    good = [
        (near, hex_("a", 40)), (near, hex_("b", 32)), (near, b64("c", 40)), (plain, F.concat(F.lit("AKIA"), F.upper(hex_("d", 16)))),
        (near, F.concat(F.lit("ghp_"), F.regexp_replace(b64("e", 36), "[+/=]", "x"))), (near, F.concat(F.lit("sk-"), F.regexp_replace(b64("f", 40), "[+/=]", "T"))),
        (near, hex_("g", 64)), (plain, F.lit("-----BEGIN RSA PRIVATE KEY-----")), (near, F.regexp_replace(b64("h", 20), "[+/=]", "9")), (plain, b64("i", 44)),
        (plain, F.concat(F.lit("AKIA"), F.translate(F.upper(hex_("q", 16)), "0123456789", "GHIJKLMNOP"))), (given, F.regexp_replace(b64("t", 12), "[+/=]", "7")),
        (given, F.concat(word("r"), F.pmod(F.xxhash64(n), F.lit(1000)), hex_("s", 4))), (given, F.concat(word("w"), F.pmod(F.xxhash64(n), F.lit(10)), F.translate(hex_("x", 4), "0123456789", "ghijklmnop"))), (given, F.concat(word("y"), word("z"), F.pmod(F.xxhash64(n), F.lit(100)))),
    ]
    bad = [
        (plain, F.concat_ws("-", word("a"), word("b"), word("c"), F.pmod(n, F.lit(100)))), (harmless, hex_("j", 40)), (harmless, hex_("k", 64)), (plain, F.concat(glued("d", 4), F.pmod(n, F.lit(1000)))),
        (near, F.lit("EXAMPLEKEY0123456789abcd")), (near, F.concat(F.lit("your_"), word("e"), F.lit("_token_here_1234"))), (plain, F.format_string("%016d", F.pmod(F.xxhash64(n), F.lit(10**16)))), (harmless, F.concat_ws("-", hex_("l", 8), hex_("m", 4), hex_("n", 4), hex_("o", 12))),
        (plain, F.concat(F.lit("chapter/"), word("f"), F.lit("/page-"), n)), (plain, F.concat(F.initcap(word("g")), F.initcap(word("h")), F.initcap(word("i")), F.initcap(word("j")))), (plain, F.concat(F.initcap(word("p")), F.lit("Is"), F.initcap(word("q")), F.lit("Of"), F.initcap(word("r")))), (plain, F.concat(F.lit("This"), F.initcap(word("s")), F.lit("A"), F.initcap(word("t")), F.lit("s"))), (plain, F.concat(glued("k", 3), F.lit("!!!"))), (near, F.concat(F.lit("xxxxxxxxxxxxxxxx"), F.pmod(n, F.lit(10)))),
        (pick("rule", "token: ", "password: ", "secret = "), glued("l", 3)), (given, F.concat(word("u"), word("v"))),
    ]
    path = pick("path", "app/main", "config/settings", "docs/readme", "tests/fixture", "web/2024/post", "")

    def case(cases: list, label: int) -> DataFrame:
        base = spark.range(0, rows // 2).select("id", F.pmod(n, F.lit(len(cases))).alias("k"), _some_words(n).alias("words"))
        take = lambda at: reduce(lambda e, i: e.when(F.col("k") == i, cases[i][at]), range(1, len(cases)), F.when(F.col("k") == 0, cases[0][at]))
        return base.select(take(1).cast("string").alias("token"), take(0).alias("before"), path.alias("path"), F.lit(float(label)).alias("label"))

    out = case(good, 1).unionByName(case(bad, 0))
    return out.select("token", "before", close(F.col("before")).alias("after"), "path", "label")


def fit(findings: DataFrame, trees: int = TREES, depth: int = DEPTH, seed: int = SEED) -> RandomForestClassificationModel:
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(features(findings)).select("features", "label")
    return RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed).fit(rows)


def _scored(df: DataFrame, model: RandomForestClassificationModel) -> DataFrame:
    rows = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(features(df))
    return model.transform(rows).withColumn("score", F.round(vector_to_array("probability")[1], 6)).drop(*FEATURES, "features", "rawPrediction", "probability", "prediction")


def _running(lengths: Column, step: int = 64) -> Column:
    """Running sums of an array, by sums of blocks of `step`, so that no prefix is copied for each element."""
    total = lambda a: F.aggregate(a, F.lit(0), lambda x, y: x + y)
    blocks = F.when(F.size(lengths) > 0, F.sequence(F.lit(0), F.floor((F.size(lengths) - 1) / step).cast("int"))).otherwise(F.array().cast("array<int>"))
    sums = F.transform(blocks, lambda b: total(F.slice(lengths, b * step + 1, F.lit(step))))
    before = F.aggregate(sums, F.array(F.lit(0)), lambda a, x: F.concat(a, F.array(F.element_at(a, -1) + x)))
    return F.transform(lengths, lambda _, i: F.get(before, F.floor(i / step).cast("int")) + total(F.slice(lengths, (F.floor(i / step) * step).cast("int") + 1, F.pmod(i, F.lit(step)) + 1)))


def candidates(docs: DataFrame) -> DataFrame:
    """doc_id, number, start (in characters), token, before, after, path for each candidate of docs(doc_id, text, source)."""
    path = F.coalesce(F.col("source").cast("string"), F.lit("")) if "source" in docs.columns else F.lit("")
    rows = docs.where(F.col("text").rlike(CANDIDATE)).select("doc_id", F.col("text").cast("string").alias("text"), path.alias("path"))
    parts, tokens = F.split("text", CANDIDATE, -1), F.regexp_extract_all("text", F.lit(CANDIDATE), F.lit(0))
    rows = rows.select("doc_id", "path", parts.alias("parts"), tokens.alias("tokens"))
    each = F.transform("tokens", lambda t, i: F.struct(t.alias("token"), F.right(F.get("parts", i), F.lit(NEAR)).alias("before"), F.left(F.get("parts", i + 1), F.lit(NEAR)).alias("after"), (F.length(F.get("parts", i)) + F.length(t)).alias("span")))
    rows = rows.select("doc_id", "path", each.alias("e"))
    rows = rows.select("doc_id", "path", "e", F.transform("e", lambda x: x["span"]).alias("spans")).select("doc_id", "path", "e", _running(F.col("spans")).alias("end"))
    rows = rows.select("doc_id", "path", F.posexplode(F.arrays_zip("e", "end")).alias("number", "c"))
    return rows.select("doc_id", "number", (F.col("c.end") - F.length("c.e.token")).alias("start"), F.col("c.e.token").alias("token"), F.col("c.e.before").alias("before"), F.col("c.e.after").alias("after"), "path")


def scan(docs: DataFrame, model: RandomForestClassificationModel | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """The findings that the forest keeps: doc_id, number, start, length, kind, score, token_sha256, shown (its two ends)."""
    model = model or fit(labelled_findings(docs.sparkSession))
    rows = _scored(candidates(docs), model).where(F.col("score") >= threshold)
    kind = F.when(F.col("token").startswith("-----BEGIN"), "private-key").when(F.col("token").rlike("^[0-9a-fA-F]+$"), "hex").when(F.col("token").rlike("^(AKIA|ASIA)[0-9A-Z]{16}$"), "access-key").otherwise("string")
    shown = F.concat(F.left("token", F.lit(3)), F.lit("..."), F.right("token", F.lit(2)))
    return rows.select(F.col("doc_id").cast("long").alias("doc_id"), "number", "start", F.length("token").alias("length"), kind.alias("kind"), "score", F.sha2("token", 256).alias("token_sha256"), shown.alias("shown"))


def redact(docs: DataFrame, model: RandomForestClassificationModel | None = None, threshold: float = THRESHOLD, mask: str = "[secret]") -> DataFrame:
    """docs with each kept finding in text replaced by mask; all columns and rows stay, n_chars follows the text."""
    model = model or fit(labelled_findings(docs.sparkSession))
    columns = docs.columns
    free = lambda name: next(x for x in (name + "_" * k for k in range(len(columns) + 1)) if x not in columns)
    key, numbers = free("text_key"), free("secret_numbers")
    has_source = "source" in columns
    keyed = docs.withColumn(key, F.xxhash64(F.col("text").cast("string"), F.coalesce(F.col("source").cast("string"), F.lit("")) if has_source else F.lit("")))
    # Findings follow from text and source, so equal rows share them; ids need not be there or be distinct.
    cand = candidates(keyed.select(F.struct(F.coalesce(F.col("doc_id"), F.lit(0)).alias("id"), F.col(key).alias("key")).alias("doc_id"), "text", *(["source"] if has_source else [])))
    hits = _scored(cand, model).where(F.col("score") >= threshold)
    hits = hits.groupBy(F.col("doc_id.id").alias("of_id"), F.col("doc_id.key").alias("of_key")).agg(F.collect_set("number").alias(numbers))
    hits = materialise(hits, "secrets")
    hits = F.broadcast(hits) if hits.count() <= BROADCAST_IDS else hits
    out = keyed.join(hits, (F.coalesce(keyed["doc_id"], F.lit(0)) == F.col("of_id")) & (keyed[key] == F.col("of_key")), "left").drop("of_id", "of_key")
    parts, tokens = F.split("text", CANDIDATE, -1), F.regexp_extract_all("text", F.lit(CANDIDATE), F.lit(0))
    clean = F.array_join(F.transform(parts, lambda p, i: F.concat(p, F.when(F.array_contains(numbers, i), F.lit(mask)).otherwise(F.coalesce(F.get(tokens, i), F.lit(""))))), "")
    same = F.col(numbers).isNull()
    out = out.withColumn("text", F.when(same, F.col("text")).otherwise(clean))
    if "n_chars" in columns:
        out = out.withColumn("n_chars", F.when(same, F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return out.select(*(f"`{c}`" for c in columns))
