"""Whole texts to token ids with the tokenizers library, each distinct piece of text encoded once per worker.

Both vocabularies split a text before any merge, and no token reaches over such a split. A text of plain Latin
letters, visible ASCII and single white space is cut around its letter runs (with the space before them, where the
vocabulary keeps it, and with apostrophes inside); any other text only at spaces between two visible characters. Pieces
are found, hashed and looked up on the byte arrays of a whole block; new ones are encoded together, and the ids are
gathered from a pool that is kept, within a bound, for the worker's next block. The ids equal those of encoding the whole text.

The library finds a vocabulary's special strings in a text before all else and gives them their own id; here each is a
piece of its own, and the text around it is cut there. With special_as_text they are ordinary text instead.
"""

from __future__ import annotations

import json
import os
from functools import lru_cache

import numpy as np
import pyarrow as pa

from spatial_links.llm import textops as T

CACHE_ENTRIES, AT_ONCE = 700_000, 20_000
#: Bytes of text encoded together.
BLOCK_BYTES = 3 << 20

_SPACES = np.zeros(256, bool)
_SPACES[[0x20, 0x0A]] = True
_LETTERS = np.zeros(256, bool)  # of plain texts, whose other bytes are ASCII
_LETTERS[[*range(65, 91), *range(97, 123), *range(128, 256)]] = True
_STRANGE = np.ones(256, bool)
_STRANGE[[0x0A, *range(0x20, 0x7F), *range(0x80, 0xC0), 0xC3, 0xC4, 0xC5]] = False
_VISIBLE = np.zeros(256, bool)
_VISIBLE[range(0x21, 0x7F)] = True
_LATIN = np.zeros(256, bool)
_LATIN[[0xC3, 0xC4, 0xC5]] = True


@lru_cache(maxsize=4)
def _tokenizer(path: str, special_as_text: bool = False):
    """(tokenizer, whether words end in a mark and case and white space are dropped, ids that start or end a word, special strings)."""
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
    from tokenizers import Tokenizer

    found = Tokenizer.from_file(path)
    found.encode_special_tokens = special_as_text
    ends = json.loads(found.to_str())["model"].get("end_of_word_suffix")
    vocabulary = found.get_vocab()
    edge = np.zeros(max(vocabulary.values()) + 1, bool)
    edge[[i for w, i in vocabulary.items() if (w.endswith(ends) if ends else w.startswith("Ġ"))]] = True
    special = [] if special_as_text else [t.content.encode() for t in found.get_added_tokens_decoder().values()]
    return found, bool(ends), edge, special


def occurrences(raw: np.ndarray, off: np.ndarray, strings: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(start, end) of the special strings inside documents, leftmost first where any would overlap."""
    whole, found = raw.tobytes(), []
    for x in strings:
        at = whole.find(x)
        while at >= 0:
            found.append((at, at + len(x)))
            at = whole.find(x, at + 1)
    spans, reached = [], 0
    for a, b in sorted(found):
        if a >= reached and np.searchsorted(off, a, "right") == np.searchsorted(off, b - 1, "right"):
            spans.append((a, b))
            reached = b
    return tuple(np.array(spans, np.int64).reshape(-1, 2).T)


def pieces(raw: np.ndarray, off: np.ndarray, bare: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, document) of the pieces of each document; bare: white space between pieces is left out."""
    n = len(raw)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, z
    first = np.zeros(n + 1, bool)
    first[off] = True
    first = first[:n]
    before, after = np.empty(n, np.uint8), np.empty(n, np.uint8)
    before[1:], after[:-1] = raw[:-1], raw[1:]
    before[0] = after[-1] = 0x0B
    before[first] = 0x0B  # a document's edge is like a separator
    after[:-1][first[1:]] = 0x0B
    letter = _LETTERS[raw]
    mark = raw == 0x27
    strange = _STRANGE[raw] | ((raw == 0xC3) & ((after == 0x97) | (after == 0xB7))) | ((raw == 0xC5) & (after == 0xBF))
    strange |= mark & _LETTERS[after] & ~_LETTERS[before] & (before != 0x27)
    if not bare:
        strange |= _SPACES[raw] & _SPACES[after]
    own = np.searchsorted(off, np.flatnonzero(strange), side="right") - 1
    odd = np.zeros(len(off) - 1, bool)
    odd[own] = True
    letter |= mark & _LETTERS[before] & _LETTERS[after]
    change = np.zeros(n, bool)
    change[1:] = letter[1:] != letter[:-1]
    start = first | change
    gap = np.zeros(n, bool)
    if bare:
        gap = _SPACES[raw]
        start[1:] |= gap[:-1]
        start &= ~gap
    else:
        joined = np.flatnonzero((raw[:-1] == 0x20) & letter[1:] & ~first[1:])
        start[joined + 1] = False
        start[joined] = True
    if odd.any():
        inside = np.repeat(odd, np.diff(off))
        ends_visible = np.zeros(n, bool)
        ends_visible[1:] = _VISIBLE[raw[:-1]]
        ends_visible[2:] |= (raw[1:-1] >= 0x80) & _LATIN[raw[:-2]]
        ends_visible &= ~first
        cut = first | ((raw == 0x20) & ends_visible & (_VISIBLE[after] | _LATIN[after]))
        start = np.where(inside, cut, start)
        gap &= ~inside
    s = np.flatnonzero(start)
    stop = np.zeros(n + 1, bool)
    stop[s] = True
    stop[off] = True
    stop[:n] |= gap
    where = np.flatnonzero(stop)
    e = where[np.searchsorted(where, s, side="right")]
    return s, e, np.searchsorted(off, s, side="right") - 1


class Encoder:
    def __init__(self, path: str, end_id: int, entries: int = CACHE_ENTRIES, special_as_text: bool = False):
        self.entries = entries
        self.tokenizer, self.bare, self.edge, self.special = _tokenizer(path, special_as_text)
        self.end = end_id
        self._clear()

    def _clear(self) -> None:
        self.slot: dict[int, int] = {}
        self.first, self.size, self.pool = np.zeros(1024, np.int64), np.zeros(1024, np.int64), np.zeros(4096, np.uint32)
        self.used = 0

    def _keep(self, keys: list[int], ids: np.ndarray, sizes: np.ndarray) -> None:
        k, n = len(self.slot), len(keys)
        while k + n > len(self.first):
            self.first, self.size = (np.concatenate([a, np.zeros(len(a), np.int64)]) for a in (self.first, self.size))
        while self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros(len(self.pool), np.uint32)])
        self.pool[self.used : self.used + len(ids)] = ids
        self.first[k : k + n] = self.used + np.cumsum(sizes) - sizes
        self.size[k : k + n] = sizes
        self.used += len(ids)
        self.slot.update(zip(keys, range(k, k + n), strict=True))

    def _learn(self, keys: list[int], texts: list[str]) -> None:
        """Words are encoded as one text, whose ids are cut where a word starts or ends; other pieces one by one."""
        is_word = (lambda p: p.isalpha()) if self.bare else (lambda p: p[:1] == " " and p[1:].isalpha())
        word, other = [], []
        for kp in zip(keys, texts, strict=True):
            (word if is_word(kp[1]) else other).append(kp)
        for at in range(0, len(word), AT_ONCE):
            part = word[at : at + AT_ONCE]
            ids = np.array(self.tokenizer.encode_batch_fast([(" " if self.bare else "").join(p for _, p in part)], add_special_tokens=False)[0].ids, np.uint32)
            edge = np.flatnonzero(self.edge[ids])
            cut = np.append(0, edge + 1) if self.bare else np.append(edge, len(ids))
            if len(cut) != len(part) + 1 or cut[0] or cut[-1] != len(ids):
                other += part
                continue
            self._keep([k for k, _ in part], ids, np.diff(cut))
        for at in range(0, len(other), AT_ONCE):
            part = other[at : at + AT_ONCE]
            got = [e.ids for e in self.tokenizer.encode_batch_fast([p for _, p in part], add_special_tokens=False)]
            self._keep([k for k, _ in part], np.array([i for x in got for i in x], np.uint32), np.array([len(x) for x in got], np.int64))

    def _pieces(self, raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a, b = occurrences(raw, off, self.special)
        if not len(a):
            return pieces(raw, off, self.bare)
        start, end, _ = pieces(raw, np.unique(np.concatenate([off, a, b])), self.bare)
        k = np.searchsorted(a, start, "right") - 1
        outside = (k < 0) | (start >= b[np.maximum(k, 0)])
        start, end = np.concatenate([start[outside], a]), np.concatenate([end[outside], b])
        order = np.argsort(start)
        return start[order], end[order], np.searchsorted(off, start[order], "right") - 1

    def block(self, raw: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ends): the ids of all documents of a block, each followed by the end id, and where each document's end."""
        start, end, doc = self._pieces(raw, off)
        key, at, inverse = np.unique(T.span_hash(raw, start, end), return_index=True, return_inverse=True)
        names = key.tolist()
        get = self.slot.get
        place = np.fromiter((get(k, -1) for k in names), np.int64, len(names))
        new = np.flatnonzero(place < 0)
        if len(self.slot) + len(new) > self.entries:
            self._clear()
            new = np.arange(len(names))
        if len(new):
            spans = zip(start[at[new]].tolist(), end[at[new]].tolist(), strict=True)
            whole, unknown = raw.tobytes(), [names[i] for i in new.tolist()]
            self._learn(unknown, [whole[a:b].decode() for a, b in spans])
            place[new] = np.fromiter(map(self.slot.__getitem__, unknown), np.int64, len(unknown))
        slot = place[inverse]
        size = self.size[slot]
        total = int(size.sum())
        before = np.cumsum(size) - size
        tokens = np.bincount(doc, weights=size, minlength=len(off) - 1).astype(np.int64) + 1
        out = np.full(total + len(off) - 1, self.end, np.uint32)
        run = np.arange(total)
        out[run + np.repeat(doc, size)] = self.pool[run + np.repeat(self.first[slot] - before, size)]
        return out, np.concatenate([[0], np.cumsum(tokens)])

    def __call__(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text as little-endian unsigned 32-bit integers."""
        ids, ends = self.block(*T.string_parts(pa.array(texts, pa.string())))
        return [ids[a:b].astype("<u4").tobytes() for a, b in zip(ends[:-1], ends[1:], strict=True)]


_encoders: dict[tuple[str, int, int], Encoder] = {}


def encoder(path: str, end_id: int, entries: int = CACHE_ENTRIES) -> Encoder:
    """One encoder, and so one pool, for each Python worker."""
    if (path, end_id, entries) not in _encoders:
        _encoders.clear()
        _encoders[path, end_id, entries] = Encoder(path, end_id, entries)
    return _encoders[path, end_id, entries]
