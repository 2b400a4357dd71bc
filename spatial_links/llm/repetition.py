"""Quality rules on repetition inside a text, by suffix arrays over words.

For a block of whole documents one suffix array is built at a time by prefix doubling, whose first key is the pair
(document, word), so no common prefix crosses two documents; only suffixes that are still tied are sorted again. The
longest common prefixes of neighbours come from the kept ranks of each doubling. A suffix's largest neighbour value
is the longest repeat that starts there (its deepest longest-common-prefix interval), and the union of these spans is
the union of all occurrences of maximal repeated substrings. A document is rejected if repeats of `min_words` words or
more cover over `max_covered` of its words, or the longest repeat has over `max_longest` words, however long the
document (a share of it would add nothing: two copies of over half of `max_covered` are too much covered already).

Nulls and empty texts have no words and fail the base rules. A document's rows depend on its text alone, so ties and
repeated rows are alike; a very long text makes a block of its own. One pass, no shuffle.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spatial_links.llm import textops as T

MIN_WORDS, MAX_COVERED, MAX_LONGEST = 8, 0.3, 100
MIN_TEXT_WORDS, MAX_REPEAT_PERCENT = 50, 50
_U = np.uint64
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True
SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "longest_repeat long, covered_words long"
)


def longest_repeats(doc: np.ndarray, word: np.ndarray) -> np.ndarray:
    """For each word, how many words from there on also stand elsewhere in the same document.

    doc: the document of each word, ascending; word: a number for each word, equal for equal words.
    """
    n = len(doc)
    if n < 2:
        return np.zeros(n, np.int64)
    last = np.searchsorted(doc, doc, side="right")  # end of the document
    order = np.lexsort((word, doc))
    new = np.ones(n, bool)
    new[1:] = (doc[order][1:] != doc[order][:-1]) | (word[order][1:] != word[order][:-1])
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(new, np.arange(n), 0))
    levels, half = [rank], 1
    alone = np.ones(n, bool)
    alone[order] = new & np.append(new[1:], True)
    active = np.flatnonzero(~alone)
    while len(active):
        ahead = active + half
        second = np.where(ahead < last[active], rank[np.minimum(ahead, n - 1)], -1)
        order = np.lexsort((second, rank[active]))
        a, s = active[order], second[order]
        r = rank[a]
        group, part = np.ones(len(a), bool), np.ones(len(a), bool)
        group[1:] = r[1:] != r[:-1]
        part[1:] = group[1:] | (s[1:] != s[:-1])
        at = np.arange(len(a))
        rank = rank.copy()
        rank[a] = r + np.maximum.accumulate(np.where(part, at, 0)) - np.maximum.accumulate(np.where(group, at, 0))
        levels.append(rank)
        half *= 2
        active = np.sort(a[~(part & np.append(part[1:], True))])
    suffix = np.empty(n, np.int64)
    suffix[rank] = np.arange(n)
    a, b = suffix[:-1], suffix[1:]
    common = np.zeros(n - 1, np.int64)
    near = np.flatnonzero(levels[0][a] == levels[0][b])
    for k in range(len(levels) - 1, -1, -1):
        x, y = a[near] + common[near], b[near] + common[near]
        ok = (x < last[a[near]]) & (y < last[b[near]])
        ok &= levels[k][np.minimum(x, n - 1)] == levels[k][np.minimum(y, n - 1)]
        common[near[ok]] += 1 << k
    out = np.zeros(n, np.int64)
    out[a] = common
    out[b] = np.maximum(out[b], common)
    return out


def union_length(doc: np.ndarray, size: np.ndarray, n_docs: int) -> np.ndarray:
    """Words of each document under the union of the spans [i, i + size[i])."""
    n = len(doc)
    at = np.flatnonzero(size)
    edge = np.zeros(n + 1, np.int64)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + size[at], -1)
    return np.bincount(doc, weights=np.cumsum(edge)[:n] > 0, minlength=n_docs).astype(np.int64)


def measures(raw: np.ndarray, off: np.ndarray, min_words: int) -> list[np.ndarray]:
    """The columns of SCHEMA after doc_id, for a block."""
    m = len(off) - 1
    start, end, doc = T.words(raw, off)
    word = T.span_hash(raw, start, end)
    n = np.bincount(doc, minlength=m)
    head = (raw & 0xC0) != 0x80
    heads = np.concatenate([[0], np.cumsum(head)])
    chars = np.bincount(doc, weights=heads[end] - heads[start], minlength=m).astype(np.int64)
    symbols = np.concatenate([[0], np.cumsum(_SYMBOL[raw])])
    symbols = symbols[off[1:]] - symbols[off[:-1]]

    ls, le, ld = T.lines(raw, off)
    seen = np.concatenate([[0], np.cumsum(~T.SPACE[raw])])
    full = seen[le] > seen[ls]
    ls, le, ld = ls[full], le[full], ld[full]
    key = T.mix(T.span_hash(raw, ls, le) + T.mix(ld.astype(np.uint64)))
    dup = np.ones(len(key), bool)
    dup[np.unique(key, return_index=True)[1]] = False
    dup_lines = np.bincount(ld[dup], minlength=m)

    repeat = np.zeros(m, np.int64)
    if len(word) >= 3:
        own = np.flatnonzero(doc[2:] == doc[:-2])
        key = T.mix(T.mix(T.mix(word[own] + T.mix(doc[own].astype(np.uint64))) ^ word[own + 1]) ^ (word[own + 2] * _U(3)))
        _, inverse, count = np.unique(key, return_inverse=True, return_counts=True)
        size = np.zeros(len(word), np.int64)
        size[own[count[inverse] > 1]] = 3
        repeat = union_length(doc, size, m)

    size = longest_repeats(doc, word)
    longest = np.zeros(m, np.int64)
    np.maximum.at(longest, doc, size)
    size[size < min_words] = 0
    return [n, chars, symbols, dup_lines, repeat, longest, union_length(doc, size, m)]


def _measure(min_words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, off in T.blocks(batches):
            names = [c.split()[0] for c in SCHEMA.split(", ")]
            yield pa.RecordBatch.from_arrays([rows.column(0), *(pa.array(x.astype(np.int64)) for x in measures(raw, off, min_words))], names=names)

    return run


def _good(column: str, min_words: int, max_covered: float, max_longest: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, raw, off in T.blocks(batches, column):
            n, _, _, _, repeat, longest, covered = measures(raw, off, min_words)
            bad = (n < MIN_TEXT_WORDS) | (100 * repeat > MAX_REPEAT_PERCENT * n)
            bad |= (covered > max_covered * n) | (longest > max_longest)
            yield rows.filter(pa.array(~bad))

    return run


def keep_good(docs: DataFrame, min_words: int = MIN_WORDS, max_covered: float = MAX_COVERED, max_longest: int = MAX_LONGEST) -> DataFrame:
    """The rows of docs, with all columns, that `quality_rules` keeps; decided where they are read, without a join."""
    return docs.mapInArrow(_good("text", min_words, max_covered, max_longest), docs.schema)


def quality_rules(docs: DataFrame, min_words: int = MIN_WORDS, max_covered: float = MAX_COVERED, max_longest: int = MAX_LONGEST) -> DataFrame:
    """SCHEMA with base_failed and kept for every row of docs(doc_id, text); other columns are ignored."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = docs.mapInArrow(_measure(min_words), SCHEMA)
    failed = (F.col("n_words") < MIN_TEXT_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))
    over = (F.col("covered_words") > max_covered * F.col("n_words")) | (F.col("longest_repeat") > max_longest)
    return out.withColumn("base_failed", failed).withColumn("kept", ~failed & ~over)
