"""Language-model scores by online logistic context mixing, beside an add-one word model.

The model predicts the lower-cased bytes of a text and an end byte, bit by bit. Predictors for contexts of 0 to 5
bytes keep counts of zeros and ones in hashed tables of a fixed size. A mixer adds their log odds with weights from the
set that a gate picks (longest context seen, and how often), and an adaptive table refines the mixed probability by gate
and value. Weights and refinement are learned online: each partition goes through its training strings in order, predicts
every bit with what it has learned so far, and moves the weights and the table's entry towards the bit; the partitions'
weights are averaged and their tables added, twice. In training, a string's own occurrence is left out of the counts it is
predicted from. Strings are dealt by a hash of all their bytes, so common endings make no large task.

What is gathered from the corpus: counts of all words and all strings of 6 bytes, summed over training texts, which
grows with the input. What reaches one place has a fixed size: the slot tables, the weights, and the commonest
`COMMON_WORDS` words (and scores of the commonest `COMMON_STRINGS` strings), which are looked up where texts are read; all other words are joined with their counts, so the
base score is exact for any vocabulary. A text's score is a sum over its distinct strings, computed once a block.

Null and empty texts are one end token (and end byte). Repeated rows are separate rows. With no training text the
counts are zero: base 0, score of an untrained model. Very long texts make a block of their own. Rows without a doc_id are
scored, and counted as training texts. Counts of slots are kept in steps of a sixth of a power of two, up to 6e12.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spatial_links.llm import textops as T
from spatial_links.llm.common import materialise, partitions

_U = np.uint64
ORDERS = 6
#: Slots of each order's table, as powers of two.
SLOT_BITS = (8, 14, 18, 20, 21, 22)
BASE = np.concatenate([[0], np.cumsum([1 << b for b in SLOT_BITS])])
GATES, STEPS, LEARN, ROUNDS, CODE_STEPS, PRIOR_BITS = 4 * ORDERS + 1, 33, 0.02, 2, 6, 50.0
COMMON_WORDS, COMMON_STRINGS, PENDING = 1 << 20, 1 << 20, 600_000
END_BYTE = 0xFF
END_TOKEN = int(T.mix(np.array([12345], np.uint64))[0])
WORD, GRAM = 0, 1


def grams(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(strings of ORDERS bytes as integers, document): one for each byte of each text and one for its end byte."""
    m, past = len(off) - 1, ORDERS - 1
    size = np.diff(off)
    to = off[:-1] + ORDERS * np.arange(m)  # each text is put after `past` end bytes and before one
    x = np.full(int(off[-1]) + ORDERS * m, END_BYTE, np.uint8)
    own = np.repeat(np.arange(m), size)
    x[np.arange(len(raw)) + ORDERS * own + past] = T.LOWER[raw]
    key = np.zeros(max(len(x) - past, 0), np.uint64)
    for j in range(ORDERS):
        key = (key << _U(8)) | x[j : len(x) - past + j]
    doc = np.repeat(np.arange(m), size + 1)
    return key[np.arange(len(doc)) - np.repeat(np.cumsum(size + 1) - size - 1, size + 1) + np.repeat(to, size + 1)], doc


def word_hashes(raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    low = T.LOWER[raw]
    start, end, doc = T.words(low, off)
    return T.span_hash(low, start, end), doc


class _Sums:
    """Counts of keys, merged until there are too many to hold."""

    def __init__(self):
        self.keys, self.counts, self.size = [], [], 0

    def add(self, keys: np.ndarray, counts: np.ndarray | None = None):
        k, at = (np.unique(keys, return_counts=True)) if counts is None else (keys, counts)
        self.keys.append(k)
        self.counts.append(at.astype(np.int64))
        self.size += len(k)

    def merged(self) -> tuple[np.ndarray, np.ndarray]:
        if not self.keys:
            return np.zeros(0, np.uint64), np.zeros(0, np.int64)
        k, n = np.concatenate(self.keys), np.concatenate(self.counts)
        order = np.argsort(k)
        k, n = k[order], n[order]
        at = np.flatnonzero(np.append(True, k[1:] != k[:-1])) if len(k) else np.zeros(0, np.int64)
        self.keys, self.counts = [k[at]], [np.add.reduceat(n, at) if len(at) else n]
        self.size = len(at)
        return self.keys[0], self.counts[0]

    def full(self) -> bool:
        if self.size > 2 * PENDING:
            self.merged()
        return self.size > PENDING


def _batch(kind: int, keys: np.ndarray, counts: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), kind, np.int32)), pa.array(np.ascontiguousarray(keys).view(np.int64)), pa.array(counts)], names=["kind", "key", "n"])


def _gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sums = {WORD: _Sums(), GRAM: _Sums()}
    for rows, raw, off in T.blocks(batches):
        sums[WORD].add(word_hashes(raw, off)[0])
        sums[WORD].add(np.array([END_TOKEN], np.uint64), np.array([rows.num_rows]))
        sums[GRAM].add(grams(raw, off)[0])
        for kind, s in sums.items():
            if s.full():
                yield _batch(kind, *s.merged())
                sums[kind] = _Sums()
    for kind, s in sums.items():
        keys, counts = s.merged()
        for at in range(0, len(keys), 200_000):
            yield _batch(kind, keys[at : at + 200_000], counts[at : at + 200_000])


def contexts(key: np.ndarray) -> list[np.ndarray]:
    """For each order, a hash of that many bytes before the last of each string."""
    before = key >> _U(8)
    return [T.mix((before & _U((1 << (8 * o)) - 1)) + _U(o << 56)) if o else np.zeros(len(key), np.uint64) for o in range(ORDERS)]


def slot(order: int, context: np.ndarray, node: np.ndarray) -> np.ndarray:
    if order == 0:
        return node.astype(np.int64)
    mixed = (context + node * _U(0x9E3779B97F4A7C15)) * _U(0xD6E8FEB86659FD93)
    return (mixed >> _U(64 - SLOT_BITS[order])).astype(np.int64) + BASE[order]


def _slots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of zeros and ones of the slots that a partition's strings touch, as keys 2 * slot + bit."""
    sums = _Sums()
    for b in batches:
        keys, n = b.column(0).to_numpy().view(np.uint64), b.column(1).to_numpy()
        for lo in range(0, len(keys), 40_000):
            k, c = keys[lo : lo + 40_000], n[lo : lo + 40_000]
            ctx, sym = contexts(k), k & _U(255)
            for o in range(ORDERS):
                for bit in range(8):
                    node = (_U(1) << _U(bit)) | (sym >> _U(8 - bit))
                    part = _Sums()
                    part.add((2 * slot(o, ctx[o], node)).view(np.uint64) + ((sym >> _U(7 - bit)) & _U(1)), c)
                    sums.add(*part.merged())
            if sums.full():
                yield _batch(GRAM, *sums.merged())
                sums = _Sums()
    yield _batch(GRAM, *sums.merged())


def _code(counts: np.ndarray) -> np.ndarray:
    return np.minimum(255, np.rint(CODE_STEPS * np.log2(1 + counts))).astype(np.uint8)


_COUNT = 2.0 ** (np.arange(256) / CODE_STEPS) - 1


class Mixer:
    """Slot tables, weights and the refining table."""

    def __init__(self, zeros: np.ndarray, ones: np.ndarray):
        self.zeros, self.ones = zeros, ones  # codes of counts
        self.weights = np.zeros((GATES, ORDERS + 1), np.float32)
        self.weights[:, :ORDERS] = 0.3
        self.refine = np.tile(_squash(_grid()), (GATES, 1)).astype(np.float32)
        #: Bits per byte that each round predicted its training strings with while it learned.
        self.losses: list[float] = []

    def inputs(self, ctx: list[np.ndarray], sym: np.ndarray, bit: int, leave_out: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(log odds of each order, gate, the bit) at one bit of each string."""
        node = (_U(1) << _U(bit)) | (sym >> _U(8 - bit))
        y = ((sym >> _U(7 - bit)) & _U(1)).astype(np.float32)
        x = np.empty((len(sym), ORDERS + 1), np.float32)
        x[:, ORDERS] = 0.3
        gate = np.zeros(len(sym), np.int64)
        for o in range(ORDERS):
            at = slot(o, ctx[o], node)
            zero, one = self.zeros[at], self.ones[at]
            if leave_out:
                n0, n1 = _COUNT[zero], _COUNT[one]
                n0, n1 = np.maximum(n0 - (1 - y), 0), np.maximum(n1 - y, 0)
                x[:, o] = np.log((n1 + 0.4) / (n0 + 0.4))
                n = n0 + n1
                level = np.where(n >= 16, 4, np.where(n >= 4, 3, np.where(n >= 1.5, 2, np.where(n >= 0.5, 1, 0))))
            else:
                pair = (zero.astype(np.int64) << 8) | one
                x[:, o] = _ODDS[pair]
                level = _LEVEL[pair]
            gate = np.where(level > 0, 4 * o + level, gate)
        return x, gate, y

    def mixed(self, x: np.ndarray, gate: np.ndarray) -> np.ndarray:
        return np.clip(np.einsum("ij,ij->i", x, self.weights[gate]), -11.5, 11.5)

    def refined(self, odds: np.ndarray, gate: np.ndarray) -> np.ndarray:
        """Probability of a one: the mean of the mixed value and its refinement, interpolated between steps."""
        at = (odds + 12) * ((STEPS - 1) / 24)
        low = at.astype(np.int64)
        part = (at - low).astype(np.float32)
        r = self.refine[gate, low] * (1 - part) + self.refine[gate, low + 1] * part
        return np.clip(0.5 * (_squash(odds) + r), 1e-6, 1 - 1e-6)

    def log10(self, key: np.ndarray) -> np.ndarray:
        """log10 of the probability of each string's last byte after the others."""
        out = np.zeros(len(key))
        for lo in range(0, len(key), 32_768):
            k = key[lo : lo + 32_768]
            ctx, sym = contexts(k), k & _U(255)
            p = np.ones(len(k))
            for bit in range(8):
                x, gate, y = self.inputs(ctx, sym, bit, False)
                one = self.refined(self.mixed(x, gate), gate)
                p *= np.where(y > 0, one, 1 - one)
            out[lo : lo + 32_768] = np.log10(p)
        return out


def _grid() -> np.ndarray:
    return np.linspace(-12, 12, STEPS)


def _squash(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-x))


_ODDS = np.log((_COUNT[None, :] + 0.4) / (_COUNT[:, None] + 0.4)).astype(np.float32).ravel()
_N = (_COUNT[None, :] + _COUNT[:, None]).ravel()
_LEVEL = np.where(_N >= 16, 4, np.where(_N >= 4, 3, np.where(_N >= 1.5, 2, np.where(_N >= 0.5, 1, 0)))).astype(np.int64)


def _strings(batches: Iterator[pa.RecordBatch], size: int):
    for b in batches:
        keys, n = b.column(0).to_numpy().view(np.uint64), b.column(1).to_numpy()
        for lo in range(0, len(keys), size):
            yield keys[lo : lo + size], n[lo : lo + size].astype(np.float32)


def _learn(shared):
    """An online pass over a partition's strings; yields its weights, each set with the bits it was learned from, and its table."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mixer: Mixer = shared.value
        own = Mixer(mixer.zeros, mixer.ones)
        own.weights, seen = mixer.weights.astype(float), np.zeros(GATES)
        energy = np.full(own.weights.shape, 1e-3)
        bits, ones = np.zeros(GATES * STEPS), np.zeros(GATES * STEPS)
        loss, total = 0.0, 0.0
        for keys, n in _strings(batches, 2048):
            ctx, sym = contexts(keys), keys & _U(255)
            for bit in range(8):
                x, gate, y = own.inputs(ctx, sym, bit, True)
                odds = own.mixed(x, gate)
                one = own.refined(odds, gate)
                loss -= float((n * np.log2(np.where(y > 0, one, 1 - one))).sum())
                push = x * ((y - _squash(odds)) * n)[:, None]
                step = np.zeros_like(own.weights)
                np.add.at(step, gate, push)
                mass = np.bincount(gate, weights=n, minlength=GATES)
                step /= np.maximum(mass, 1)[:, None]
                energy += step**2
                own.weights += LEARN * 5 * step / np.sqrt(energy)
                seen += mass
                at = gate * STEPS + np.rint((odds + 12) * ((STEPS - 1) / 24)).astype(np.int64)
                bits += np.bincount(at, weights=n, minlength=GATES * STEPS)
                ones += np.bincount(at, weights=n * y, minlength=GATES * STEPS)
                if bit == 7:
                    own.refine = _table(bits, ones)
            total += float(n.sum())
        parts = [own.weights, seen, bits, ones, np.array([loss, total])]
        yield pa.RecordBatch.from_arrays([pa.array([np.ascontiguousarray(v, float).tobytes()], pa.binary()) for v in parts], names=["weights", "seen", "bits", "ones", "loss"])

    return run


def _table(bits: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """The refining table of these sums: shares of ones, drawn to the mixed probability where few bits were seen."""
    prior = _squash(_grid())[None, :]
    return ((ones.reshape(GATES, STEPS) + PRIOR_BITS * prior) / (bits.reshape(GATES, STEPS) + PRIOR_BITS)).astype(np.float32)


def train(strings: DataFrame) -> Mixer:
    """From (key, n), the counts of all strings of 6 bytes of the training texts."""
    spark = strings.sparkSession
    width = max(4, partitions(spark))
    dealt = materialise(strings.repartition(width, F.xxhash64("key")).sortWithinPartitions(F.xxhash64("key", F.lit(1))), "strings")
    touched = dealt.mapInArrow(_slots, "kind int, key long, n long").groupBy("key").agg(F.sum("n").alias("n"))
    coded = touched.select(F.col("key").cast("int").alias("key"), F.least(F.lit(255), F.rint(CODE_STEPS * F.log2(1 + F.col("n")))).cast("short").alias("code"))
    got = coded.toArrow()
    zeros, ones = np.zeros(int(BASE[-1]), np.uint8), np.zeros(int(BASE[-1]), np.uint8)
    key, code = got.column(0).to_numpy(), got.column(1).to_numpy().astype(np.uint8)
    zeros[key[key % 2 == 0] // 2] = code[key % 2 == 0]
    ones[key[key % 2 == 1] // 2] = code[key % 2 == 1]
    mixer = Mixer(zeros, ones)
    for _ in range(ROUNDS):
        shared = spark.sparkContext.broadcast(mixer)
        parts = dealt.select("key", "n").mapInArrow(_learn(shared), "weights binary, seen binary, bits binary, ones binary, loss binary").collect()
        of = lambda c: np.array([np.frombuffer(r[c]) for r in parts])
        mass, each = of("seen"), of("weights").reshape(-1, GATES, ORDERS + 1)
        some = mass.sum(0) > 0
        mean = (each * mass[:, :, None]).sum(0) / np.maximum(mass.sum(0), 1)[:, None]
        mixer.weights = np.where(some[:, None], mean, mixer.weights).astype(np.float32)
        mixer.refine = _table(of("bits").sum(0), of("ones").sum(0))
        mixer.losses.append(float(of("loss")[:, 0].sum() / max(1.0, of("loss")[:, 1].sum())))
        shared.destroy()
    return mixer


def least_count(counts: DataFrame, most: int) -> int:
    """The least n for which at most `most` rows of (key, n) have that many or more."""
    level = F.ceil(F.log2(F.col("n")) * 4).cast("int")
    sizes = {r.level: r.rows for r in counts.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("rows")).collect()}
    least, total = 1 << 62, 0
    for v in sorted(sizes, reverse=True):
        if total + sizes[v] > most:
            break
        total += sizes[v]
        least = int(np.floor(2 ** ((v - 1) / 4))) + 1 if v > 0 else 1
    return least


def _sorted_table(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """A bounded (key, value) table on the driver, keys ascending."""
    got = rows.toArrow()
    key, value = got.column(0).to_numpy().view(np.uint64), got.column(1).to_numpy()
    order = np.argsort(key)
    return key[order], value[order]


def _logs(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(shared.value.log10(b.column(0).to_numpy().view(np.uint64)))], names=["key", "log"])

    return run


def _look_up(keys: np.ndarray, values: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(found, value or 0) of each wanted key in a sorted table."""
    if not len(keys):
        return np.zeros(len(wanted), bool), np.zeros(len(wanted))
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    found = keys[at] == wanted
    return found, np.where(found, values[at], 0.0)


def _score(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        mixer, words, strings = shared.value
        for rows, raw, off in T.blocks(batches, size=2 * T.BLOCK_BYTES):
            m = rows.num_rows
            g, doc = grams(raw, off)
            u, inverse = np.unique(g, return_inverse=True)
            found, value = _look_up(*strings, u)
            value[~found] = mixer.log10(u[~found])
            score = np.bincount(doc, weights=value[inverse], minlength=m)
            del g, inverse, doc
            h, doc = word_hashes(raw, off)
            n_tokens = np.bincount(doc, minlength=m) + 1
            h, doc = np.concatenate([h, np.full(m, END_TOKEN, np.uint64)]), np.concatenate([doc, np.arange(m)])
            u, inverse = np.unique(h, return_inverse=True)
            found, value = _look_up(*words, u)
            known = found[inverse]
            n_known = np.bincount(doc[known], minlength=m)
            part = np.bincount(doc, weights=value[inverse], minlength=m)
            h, doc = h[~known], doc[~known]
            order = np.lexsort((h, doc))
            h, doc = h[order], doc[order]
            new = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (doc[1:] != doc[:-1]))) if len(h) else np.zeros(0, np.int64)
            times = np.diff(np.append(new, len(h)))
            ends = pa.array(np.concatenate([[0], np.cumsum(np.bincount(doc[new], minlength=m))]).astype(np.int32))
            rare = [pa.ListArray.from_arrays(ends, pa.array(x)) for x in (np.ascontiguousarray(h[new]).view(np.int64), times.astype(np.int64))]
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(2), pa.array(n_tokens.astype(np.int64)), pa.array(n_known.astype(np.int64)), pa.array(part), pa.array(score), pa.array(np.diff(off) + 1), *rare], names=["doc_id", "held_out", "n_tokens", "n_known", "part", "score", "n_bytes", "rare", "times"])

    return run


def scores(docs: DataFrame, parts: int = 7, held: int = 2, common: int = COMMON_WORDS) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte) for every row of docs(doc_id, text)."""
    spark = docs.sparkSession
    out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % parts == held, F.lit(False))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), out.alias("held_out"))
    counts = docs.where(~F.col("held_out")).select("doc_id", "text").mapInArrow(_gather, "kind int, key long, n long")
    counts = materialise(counts.groupBy("kind", "key").agg(F.sum("n").alias("n")), "counts")
    words = counts.where(F.col("kind") == WORD)
    total, distinct = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    strings = counts.where(F.col("kind") == GRAM).select("key", "n")
    mixer = train(strings)
    first = spark.sparkContext.broadcast(mixer)
    common_strings = _sorted_table(strings.where(F.col("n") >= least_count(strings, COMMON_STRINGS)).select("key").mapInArrow(_logs(first), "key long, log double"))
    first.destroy()
    least = least_count(words, common)
    common_words = _sorted_table(words.where(F.col("n") >= least).select("key", F.log10(F.col("n") + 1).alias("log")))
    shared = spark.sparkContext.broadcast((mixer, common_words, common_strings))
    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, part double, score double, n_bytes long, rare array<long>, times array<long>"
    scored = materialise(docs.mapInArrow(_score(shared), schema).withColumn("row", F.monotonically_increasing_id()), "scored")
    rare = scored.select("row", F.explode(F.arrays_zip("rare", "times")).alias("r")).select("row", F.col("r.rare").alias("key"), F.col("r.times").alias("times"))
    met = rare.join(words.where(F.col("n") < least).select("key", "n"), "key")
    met = met.groupBy("row").agg(F.sum("times").alias("more"), F.sum(F.col("times") * F.log10(F.col("n") + 1)).alias("rest"))
    base = F.col("part") + F.coalesce("rest", F.lit(0.0)) - F.col("n_tokens") * F.lit(float(np.log10(total + distinct + 1)))
    return scored.join(met, "row", "left").select("doc_id", "held_out", "n_tokens", (F.col("n_known") + F.coalesce("more", F.lit(0))).alias("n_known"), F.lit(int(total)).cast("long").alias("train_tokens"), base.alias("base_score"), "score", (-F.col("score") * float(np.log2(10)) / F.col("n_bytes")).alias("bits_per_byte"))
