"""License scans: base phrases by place, and an exact set-similarity join of text blocks with license templates.

Templates are sentences that name or grant a license, and license bodies (`license_texts`). A block is a line or the
whole text, or a run of words of a longer one (runs overlap by half, so whatever stands in half a run's words is whole in
some run, across line breaks too): `BLOCK_WORDS` words for sentences, `BODY_WORDS`, of the whole text, for bodies. A block
meets a template if it holds at least `percent` of the template's distinct words. All templates that it meets label it,
but one of which it holds only words that another label's template has too (gpl-2 by a text of gpl-3): without a word that
tells it from its rival it is named only if whole, or if it is the shorter of the two and no word speaks for the longer. The join orders words by their frequency in the whole corpus, rarest
first: a block that meets the threshold must share one of a template's first |T| - need + 1 words (prefix filter), must
have `need` words of the templates at all (length filter), and the words left after the first common one must suffice
(positional filter). What passes is compared in full, so the result is exact. Only DataFrame functions are used.

Templates are a fixed list, so what is broadcast does not grow. Null and empty texts give no words, no labels and
score 0. Rows equal in doc_id and text get equal results, rows without a doc_id by their text; a very long text is cut
into blocks. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from spatial_links.llm.common import small
from spatial_links.llm.license_texts import TEMPLATES

BLOCK_WORDS, BODY_WORDS, PERCENT = 64, 512, 80
#: Separators of the words of a text before lower-casing: all of ASCII but digits and letters.
SEPARATOR = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: The base phrases and their labels.
PHRASES = {"cc-by": ("cc", "by"), "gpl": ("general", "public", "license"), "reserved": ("all", "rights", "reserved")}

def _words(text: Column) -> Column:
    return F.array_remove(F.split(text, SEPARATOR), "")


def _lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def template_words() -> list[tuple[str, tuple[str, ...]]]:
    import re

    return [(label, tuple(dict.fromkeys(w for w in re.split(SEPARATOR, text.lower()) if w))) for label, text in TEMPLATES]


def run_words(words: tuple[str, ...]) -> int:
    """Words of the blocks in which a template of these distinct words is looked for."""
    return BLOCK_WORDS if len(words) <= BLOCK_WORDS // 2 else BODY_WORDS


def rivals(percent: int) -> list[list[tuple[str, ...]]]:
    """For each template, those of other labels that a block may hold most of it by."""
    every = template_words()
    return [[o for other, o in every if other != label and len(set(o) & set(ws)) >= needed(len(ws), percent)] for label, ws in every]


def needed(size: int, percent: int) -> int:
    return -(-size * percent // 100)


def frequencies(docs: DataFrame) -> dict[str, int]:
    """How often each word of the templates stands in the whole corpus; as many numbers as the templates have words."""
    vocabulary = sorted({w for _, ws in template_words() for w in ws})
    words = docs.select(F.explode(_words(F.col("text"))).alias("w")).select(F.lower("w").alias("w")).where(F.col("w").isin(vocabulary))
    return dict.fromkeys(vocabulary, 0) | {r.w: r.n for r in words.groupBy("w").agg(F.count(F.lit(1)).alias("n")).collect()}


def _places(words: Column, phrase: tuple[str, ...]) -> Column:
    def at(i: Column) -> Column:
        ok = F.lit(True)
        for k, w in enumerate(phrase):
            ok = ok & (F.get(words, i + k) == w)
        return ok

    return F.filter(F.sequence(F.lit(0), F.greatest(F.size(words) - 1, F.lit(0))), at)


def _tree(words: list[str]) -> str:
    """A pattern of any of the words, by their first letters, so that few alternatives are tried at a place."""
    if len(words) < 3:
        return "|".join(words)
    by: dict[str, list[str]] = {}
    for w in words:
        by.setdefault(w[:1], []).append(w[1:])
    return "|".join(c if rest == [""] else f"{c}(?:{_tree([w for w in rest if w])}){'?' if '' in rest else ''}" for c, rest in by.items())


def _any(words: list[str]) -> str:
    edge = "[^0-9a-zA-Z\\x80-\\x{10FFFF}]"
    return f"(?i)(?:^|{edge})(?:{_tree(words)})(?:{edge}|$)"


def base_places(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, n_words, n_base, first_word, last_word, base_labels (array)."""
    gap = SEPARATOR
    likely = "(?i)" + "|".join(gap.join(p) for p in PHRASES.values())
    none = F.array().cast("array<int>")
    words = _words(_lower(F.col("text")))
    out = docs.select("doc_id", "text_key", F.size(_words(F.col("text"))).cast("long").alias("n_words"), F.when(F.col("text").rlike(likely), words).alias("w"))
    for label, phrase in PHRASES.items():
        out = out.withColumn(label, F.when(F.col("w").isNull(), none).otherwise(_places(F.col("w"), phrase)))
    every = F.concat(*(F.col(f"`{x}`") for x in PHRASES))
    labels = F.array_compact(F.array(*(F.when(F.size(F.col(f"`{x}`")) > 0, F.lit(x)) for x in PHRASES)))
    return out.select("doc_id", "text_key", "n_words", F.size(every).cast("long").alias("n_base"), F.array_min(every).cast("long").alias("first_word"), F.array_max(every).cast("long").alias("last_word"), labels.alias("base_labels"))


def _runs(w: Column, size: int) -> Column:
    starts = F.when(F.size(w) <= size, F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.size(w) - 1, F.lit(size // 2)))
    return F.posexplode(F.transform(starts, lambda i: F.slice(w, i + 1, size))).alias("run", "words")


def blocks(docs: DataFrame, likely: dict[int, str]) -> dict[int, DataFrame]:
    """For each size doc_id, text_key, number of the line (0: the whole text), run in it, words: every block that matches likely[size]."""
    out = {}
    for size, pattern in likely.items():
        some = docs.where(F.col("text").rlike(pattern))
        lines = F.array("text") if size == BODY_WORDS else F.when(F.contains("text", F.lit("\n")), F.concat(F.array("text"), F.split("text", "\n"))).otherwise(F.array("text"))
        some = some.select("doc_id", "text_key", F.posexplode(lines).alias("number", "line")).where(F.col("line").rlike(pattern))
        out[size] = some.select("doc_id", "text_key", "number", _words(_lower(F.col("line"))).alias("w")).select("doc_id", "text_key", "number", _runs(F.col("w"), size))
    return out


def _template_table(spark: SparkSession, order: dict[str, int], percent: int) -> DataFrame:
    """(template, size, label, t_ranks, need, rivals): a handful of rows, their words as ranks (texts that are split again)."""
    ranked = lambda ws: ",".join(map(str, sorted(order[w] for w in ws)))
    rows = [(n, run_words(ws), label, ranked(ws), needed(len(ws), percent), ";".join(map(ranked, others))) for n, ((label, ws), others) in enumerate(zip(template_words(), rivals(percent), strict=True))]
    d = small(spark, rows, "template int, size int, label string, t string, need int, r string")
    numbers = lambda c: F.split(c, ",").cast("array<int>")
    others = F.when(F.col("r") == "", F.array().cast("array<array<int>>")).otherwise(F.transform(F.split("r", ";"), numbers))
    return d.select("template", "size", "label", numbers(F.col("t")).alias("t_ranks"), "need", others.alias("rivals"))


def _ranks(words: Column, order: dict[str, int]) -> Column:
    """The ranks, ascending, of those of the words that have one."""
    known, rank = F.array(*(F.lit(w) for w in order)), F.create_map(*(F.lit(x) for w in order for x in (w, order[w])))
    return F.array_sort(F.transform(F.array_intersect(words, known), lambda w: F.element_at(rank, w)))


def template_matches(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """doc_id, text_key, label, containment: every pair of a block and a template at the threshold that no rival explains, best per label."""
    count = frequencies(docs)
    order = {w: i for i, w in enumerate(sorted(count, key=lambda w: (count[w], w)))}
    words, first = {}, {}
    for _, ws in template_words():
        size, some = run_words(ws), sorted(ws, key=order.get)
        words.setdefault(size, set()).update(ws)
        first.setdefault(size, set()).update(some[: len(ws) - needed(len(ws), percent) + 1])
    table = _template_table(docs.sparkSession, order, percent)
    prefixes = table.select("template", "size", "t_ranks", "need", F.posexplode(F.slice("t_ranks", F.lit(1), F.size("t_ranks") - F.col("need") + 1)).alias("t_at", "rank"))
    found = None
    for size, part in blocks(docs, {size: _any(sorted(of)) for size, of in first.items()}).items():
        own = sorted(words[size], key=order.get)
        part = part.select("doc_id", "text_key", F.lit(size).alias("size"), "number", "run", _ranks(F.col("words"), {w: order[w] for w in own}).alias("ranks"))
        found = part if found is None else found.unionByName(part)
    pairs = found.select("*", F.posexplode("ranks").alias("at", "rank")).join(F.broadcast(prefixes), ["rank", "size"])
    pairs = pairs.where("size(ranks) >= need and 1 + least(size(t_ranks) - t_at - 1, size(ranks) - at - 1) >= need")
    pairs = pairs.select("doc_id", "text_key", "number", "run", "template", "need", "ranks", F.size("t_ranks").alias("all"), F.array_intersect("ranks", "t_ranks").alias("held")).withColumn("common", F.size("held"))
    met = pairs.where("common >= need").join(F.broadcast(table.select("template", "label", "rivals")), "template")
    alone = lambda r: (F.size(F.array_intersect("ranks", r)) == F.col("common")) & (F.col("all") < F.size(r))
    told = (F.col("common") == F.col("all")) | ~F.exists("rivals", lambda r: (F.size(F.array_except("held", r)) == 0) & ~alone(r))
    return met.where(told).groupBy("doc_id", "text_key", "label").agg(F.max(F.col("common") / F.col("all")).alias("containment"))


def scan(docs: DataFrame, percent: int = PERCENT) -> DataFrame:
    """One row per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("text_key", F.xxhash64("text"))
    best = template_matches(docs, percent).groupBy(F.col("doc_id").alias("of_id"), F.col("text_key").alias("of_text")).agg(F.collect_set("label").alias("more"), F.max("containment").alias("containment"))
    out = base_places(docs).join(best, F.col("doc_id").eqNullSafe(F.col("of_id")) & (F.col("text_key") == F.col("of_text")), "left")
    joined = lambda a: F.array_join(F.array_sort(a), ",")
    every = F.array_union("base_labels", F.coalesce("more", F.array().cast("array<string>")))
    score = F.greatest(F.coalesce("containment", F.lit(0.0)), F.when(F.col("n_base") > 0, 1.0).otherwise(0.0))
    return out.select("doc_id", "n_words", "n_base", "first_word", "last_word", joined(F.col("base_labels")).alias("base_labels"), joined(every).alias("labels"), score.alias("score"))


def oracle() -> str:
    """The same rows in DuckDB, by comparing every block with every template of its size."""
    quote = lambda ws: "[" + ", ".join(f"'{w}'" for w in ws) + "]"
    nested = lambda rs: "[" + ", ".join(quote(r) for r in rs) + "]::varchar[][]"
    templates = ", ".join(f"('{label}', {run_words(ws)}, {quote(ws)}, {needed(len(ws), PERCENT)}, {nested(rs)})" for (label, ws), rs in zip(template_words(), rivals(PERCENT), strict=True))
    vocabulary = quote(sorted({w for _, ws in template_words() for w in ws}))
    places = " ".join(
        f"union all select doc_id, i, '{label}' as label from spots where " + " and ".join(f"w[i + {k + 1}] = '{x}'" for k, x in enumerate(p))
        for label, p in PHRASES.items()
    ).removeprefix("union all ")
    cut = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
    split = lambda x: f"list_filter(regexp_split_to_array(translate({x}, '{UPPER}', '{LOWER}'), '{cut}'), lambda x: x <> '')"
    cut_up = lambda size, rows: f"select doc_id, {size} as size, w, unnest(case when len(w) <= {size} then [0] else range(0, len(w), {size // 2}) end) as i from {rows}"
    return f"""
with docs as (select doc_id, coalesce(text, '') as text, {split("coalesce(text, '')")} as w from documents),
spots as (select doc_id, w, unnest(range(0, len(w))) as i from docs),
places as ({places}),
base as (select doc_id, count(*) as n, min(i) as a, max(i) as b, string_agg(distinct label, ',' order by label) as l from places group by 1),
lines as (select doc_id, unnest(string_split(text, chr(10))) as line from docs where contains(text, chr(10))),
lw as (select doc_id, w from docs union all select doc_id, {split("line")} as w from lines),
runs as ({cut_up(BLOCK_WORDS, 'lw')} union all {cut_up(BODY_WORDS, 'docs')}),
found as (select doc_id, size, list_intersect(list_slice(w, i + 1, i + size), {vocabulary}) as ws from runs),
templates as (select * from (values {templates}) t(label, size, ws, need, rivals)),
pairs as (select f.doc_id, f.ws, t.label, t.rivals, len(t.ws) as n, list_intersect(f.ws, t.ws) as held
  from (select * from found where len(ws) >= {min(needed(len(ws), PERCENT) for _, ws in template_words())}) f join templates t on f.size = t.size and len(f.ws) >= t.need and len(list_intersect(f.ws, t.ws)) >= t.need),
hits as (select doc_id, label, len(held) / n as c from pairs
  where len(held) = n or len(list_filter(rivals, lambda r: len(list_filter(held, lambda x: not list_contains(r, x))) = 0 and not (len(list_intersect(ws, r)) = len(held) and n < len(r)))) = 0),
both_ as (select doc_id, label from hits union select doc_id, label from places),
labels as (select doc_id, string_agg(label, ',' order by label) as l from both_ group by 1),
best as (select doc_id, max(c) as c from hits group by 1)
select d.doc_id, cast(len(d.w) as bigint) as n_words, coalesce(b.n, 0) as n_base, cast(b.a as bigint) as first_word, cast(b.b as bigint) as last_word,
  coalesce(b.l, '') as base_labels, coalesce(l.l, '') as labels, cast(greatest(coalesce(h.c, 0), case when b.n > 0 then 1 else 0 end) as double) as score
from docs d left join base b using (doc_id) left join labels l using (doc_id) left join best h using (doc_id)
"""
