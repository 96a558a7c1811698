"""Removal of repeated byte strings by prefix-free parsing.

A byte goes when it lies in a ``LENGTH``-byte string that also starts earlier (smaller doc_id, or the same document further left);
strings are judged on the input and never cross documents.

*Parsing.* A rolling hash of ``GRAM``-byte grams gives the triggers: each window of ``LENGTH`` bytes belongs to the gram of least hash in it (the
leftmost of equal ones), which depends on the window's own bytes alone. Adjacent windows of one trigger make a phrase: the bytes
from the first of these windows to the end of the last. Phrases overlap by ``LENGTH - 1`` bytes, so no window is lost between two.

*Dictionary.* Equal phrases are looked up by (trigger, phrase hash): all windows of a phrase that is not the first of its kind are
repeats, without a look inside. Most repeats end here.

*Suffixes of the dictionary.* Only first phrases that share a trigger with a different phrase are opened, and their bytes gather by trigger. There the
phrases' suffixes from the trigger on, and their beginnings read backwards from it, are sorted, with the lengths that neighbours have in common: two suffix arrays
of the part of the dictionary that this trigger has. A window is its trigger's place in it, what lies before and what lies after; equal windows are those of one
run in both arrays, and the parse says which of them comes first in the corpus. Bytes are compared, not hashes of windows.

*Frequent triggers.* A trigger that a piece of text has in more than ``PER_PIECE`` different phrases, or the corpus in more than ``FREQUENT``, would gather too much
in one task. Its windows are grouped by two independent rolling hashes of their bytes instead, over all tasks.

Each map task combines before it shuffles: per ``PIECE`` of text and trigger at most ``PER_PIECE`` phrases leave, or a mark if the piece has
opened the trigger itself. So the longest list of a trigger grows with the number of pieces, not with its occurrences. Lists travel packed by hash bucket; texts
are read in pieces of bounded size, whatever a document's length.

Null and empty text: 0 bytes, nothing removed. Different texts of one doc_id count as parts of one document, in the order of their hashes; matches
do not cross parts. Exact repetitions of a row are the same place and lose the same bytes. Texts without doc_id are documents of their own,
placed by a hash of the text. Other columns are never read; an empty table gives an empty result. Phrases are known by 48 bits of their trigger's hash
and 48 of their own, windows of frequent triggers by 48 bits within a bucket (at least 8 more) and 32 of another hash: for n of them a false repeat has a
probability below n * n / 2 ** 88.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from elastipool.llm import common
from elastipool.llm.common import discard, lean, materialise, mix, prepare, table

LENGTH, GRAM = 100, 24
PIECE = 1 << 20
#: Different phrases of one trigger in a piece of text, and in the corpus, beyond which its windows are hashed.
PER_PIECE, FREQUENT = 64, 20_000
#: Bytes of small rows that are handled in one go.
TOGETHER = 1 << 19
#: Places between the parts of one document, and the most places that packed positions can tell apart.
GAP, PLACES = 1 << 10, 1 << 32
_POS_BITS = np.uint64(23)
_POS = np.uint64((1 << 23) - 1)
PHRASE, SPAN, WINDOW, OPEN, ENTRY = 0, 1, 2, 3, 4
#: A phrase's number of windows, the place of its trigger (both below 128), and whether the trigger is frequent, in one number.
_PLACE, _HASHED = 7, 1 << 14
ROWS = pa.schema([("kind", pa.int32()), ("key", pa.int64()), *((c, pa.binary()) for c in ("a", "b", "doc", "pos", "cnt"))])
ROWS_DDL = "kind int, key long, a binary, b binary, doc binary, pos binary, cnt binary"
OUT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"

#: Two hashes: a base and the value of each byte.
_BASES = (0x9E3779B97F4A7C15 | 5, 0xC2B2AE3D27D4EB4F | 5)
_BYTES = tuple(mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(c)) for c in (0xD6E8FEB86659FD93, 0xA0761D6478BD642F))
_powers: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}


def _power_table(n: int, which: int):
    """Powers of a base and of its inverse modulo 2 ** 64."""
    size = 1 << max(10, (n - 1).bit_length())
    if (which, size) not in _powers:
        base = _BASES[which]
        inv = pow(base, -1, 1 << 64)
        out = []
        for x in (base, inv):
            p = np.empty(size, np.uint64)
            p[0], filled = 1, 1
            while filled < size:
                p[filled : 2 * filled] = p[:filled] * np.uint64(pow(x, filled, 1 << 64))
                filled *= 2
            out.append(p)
        _powers[which, size] = tuple(out)
    return _powers[which, size]


class Rolling:
    """Hashes of any substring of a byte array in O(1), by the first or second hash."""

    def __init__(self, x: np.ndarray, which: int = 0):
        self.n = len(x)
        pw, self.inv = _power_table(self.n + 1, which)
        self.sums = np.zeros(self.n + 1, np.uint64)
        np.cumsum(_BYTES[which][x] * pw[: self.n], out=self.sums[1:])

    def of(self, lo, hi):
        """Hash of x[lo:hi]; arrays or slices of equal length."""
        return (self.sums[hi] - self.sums[lo]) * self.inv[lo]

    def all(self, k: int):
        return (self.sums[k:] - self.sums[:-k]) * self.inv[: self.n - k + 1]


def _phrases(x: np.ndarray, starts: np.ndarray, r: Rolling):
    """(trigger hash, phrase hash, first window, number of windows with the trigger's place) of the phrases over the window starts given."""
    h = mix(r.all(GRAM))
    k = (h & ~_POS) | np.arange(len(h), dtype=np.uint64)
    w, m, span = LENGTH - GRAM + 1, k, 1
    while span * 2 <= w:
        m = np.minimum(m[:-span], m[span:])
        span *= 2
    at = (np.minimum(m[starts], m[starts + (w - span)]) & _POS).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (starts[1:] != starts[:-1] + 1)]))
    last = np.concatenate([first[1:], [len(at)]]) - 1
    lo, hi, g = starts[first], starts[last], at[first]
    inside = mix((hi - lo).astype(np.uint64) * np.uint64(1 << 20) + (g - lo).astype(np.uint64) + np.uint64(1))
    return h[g], np.maximum(mix(r.of(lo, hi + LENGTH) ^ inside), np.uint64(1 << 16)), lo, (hi - lo + 1) | ((g - lo) << _PLACE)


def _count(code: np.ndarray) -> np.ndarray:
    return code & ((1 << _PLACE) - 1)


def _window_hashes(x: np.ndarray, r: Rolling, starts: np.ndarray):
    """Both hashes of the windows of x; r is the first of them."""
    return mix(r.of(starts, starts + LENGTH)), (mix(Rolling(x, 1).of(starts, starts + LENGTH)) >> np.uint64(32)).astype(np.uint32)


def _pieces(batches):
    """(documents, place of each part in its document, parts of texts) of (key, base, text) rows, with about PIECE bytes of text each."""
    docs, offs, parts, size = [], [], [], 0
    for b in batches:
        off, data, _ = common.byte_views(b.column(2))
        for i, (d, base) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist())):
            text = data[off[i] : off[i + 1]]
            for a in range(0, max(0, len(text) - LENGTH + 1), PIECE):
                part = text[a : a + PIECE + LENGTH - 1]
                docs.append(d)
                offs.append(base + a)
                parts.append(part.copy())
                size += len(part)
                if size >= PIECE:
                    yield docs, offs, parts
                    docs, offs, parts, size = [], [], [], 0
    if parts:
        yield docs, offs, parts


def _six(h: np.ndarray) -> np.ndarray:
    return (h >> np.uint64(16)).view(np.uint8).reshape(-1, 8)[:, :6]


def _unsix(blobs) -> np.ndarray:
    got = np.concatenate([np.frombuffer(x, np.uint8).reshape(-1, 6) for x in blobs])
    out = np.zeros((len(got), 8), np.uint8)
    out[:, :6] = got
    return out.view(np.uint64).ravel()


def _spans_by_doc(kind, doc, pos, cnt):
    """Rows of one kind, one for each document."""
    if not len(doc):
        return []
    o = np.lexsort((pos, doc))
    doc, pos, cnt = doc[o], pos[o], cnt[o]
    cuts = np.flatnonzero(np.diff(doc)) + 1
    edges = np.concatenate([[0], cuts, [len(doc)]])
    return [(kind, int(doc[a]), None, None, None, pos[a:z].astype("<u4").tobytes(), cnt[a:z].astype("<u4").tobytes()) for a, z in zip(edges[:-1].tolist(), edges[1:].tolist())]


def _by_bucket(kind, h, a, b, doc, pos, cnt, buckets):
    """Packed rows of one kind, one for each bucket of h; order inside a bucket is that of the input."""
    if not len(h):
        return []
    k = (h & np.uint64(buckets - 1)).astype(np.int64)
    o = np.argsort(k, kind="stable")
    k = k[o]
    edges = np.concatenate([[0], np.flatnonzero(np.diff(k)) + 1, [len(k)]])
    doc, pos, cnt = doc[o].astype("<i8"), pos[o].astype("<u4"), cnt[o].astype("<u2")
    a, b = np.ascontiguousarray(a[o]), np.ascontiguousarray(b[o])
    return [(kind, int(k[i]), a[i:j].tobytes(), b[i:j].tobytes(), doc[i:j].tobytes(), pos[i:j].tobytes(), cnt[i:j].tobytes()) for i, j in zip(edges[:-1].tolist(), edges[1:].tolist())]


def _firsts(keys: list[np.ndarray], doc, pos):
    """Order by keys, then corpus position; for each row whether it starts a run of equal keys, and whether it repeats the run's first place."""
    o = np.lexsort((pos, doc, *keys[::-1]))
    new = np.zeros(len(o), bool)
    new[:1] = True
    for k in keys:
        k = k[o]
        new[1:] |= k[1:] != k[:-1]
    head = np.maximum.accumulate(np.where(new, np.arange(len(o)), 0))
    d, p = doc[o], pos[o]
    return o, new, (d == d[head]) & (p == p[head])


def _first_windows(h, chk, doc, pos):
    """(rows that are the first of equal windows, rows that repeat one): one sort by hash, then the least place of each run."""
    o = np.argsort(h)
    new = np.ones(len(o), bool)
    new[1:] = h[o[1:]] != h[o[:-1]]
    starts = np.flatnonzero(new)
    run = np.cumsum(new) - 1
    if (chk[o] != chk[o[starts]][run]).any():  # different windows of one hash: sort by both
        o, new, same = _firsts([h, chk], doc, pos)
        return o[new], o[~same]
    place = (np.unique(doc, return_inverse=True)[1].astype(np.uint64) << np.uint64(32) | pos.astype(np.uint64))[o]
    least = np.minimum.reduceat(place, starts) if len(starts) else place
    same = place == least[run]
    head = np.full(len(starts), -1)
    head[run[same]] = o[same]
    return head, o[~same]


def _windows(h, chk, doc, pos, buckets):
    """First windows packed by bucket, and spans of those that repeat one of them."""
    f, later = _first_windows(h, chk, doc, pos)
    f = np.sort(f)  # in text order, so that the packed ids compress
    return _by_bucket(WINDOW, h[f], _six(h[f]), chk[f], doc[f], pos[f], np.ones(len(f)), buckets) + _spans_by_doc(SPAN, doc[later], pos[later], np.ones(len(later)))


def _of_many(t: np.ndarray, most: int) -> np.ndarray:
    """Of sorted values, those that occur more than ``most`` times."""
    edges = np.flatnonzero(np.concatenate([[True], t[1:] != t[:-1], [True]]))
    size = np.diff(edges)
    return np.repeat(size > most, size)


def _emit(rows):
    return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), ROWS)], schema=ROWS)


def _parse(buckets):
    def run(batches):
        for docs, offs, parts in _pieces(batches):
            size = np.array([len(p) for p in parts])
            base = np.concatenate([[0], np.cumsum(size)[:-1]])
            x = np.concatenate(parts)
            r = Rolling(x)
            n = size - LENGTH + 1
            part = np.repeat(np.arange(len(parts)), n)
            starts = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + base[part]
            trig, phr, lo, cnt = _phrases(x, starts, r)
            del starts, part
            p = np.searchsorted(base, lo, "right") - 1
            doc, pos = np.array(docs, np.int64)[p], lo - base[p] + np.array(offs, np.int64)[p]
            o, new, same = _firsts([trig, phr], doc, pos)
            later, first = o[~same], o[new]
            rows = _spans_by_doc(SPAN, doc[later], pos[later], _count(cnt[later]))
            many = _of_many(trig[first], PER_PIECE)
            opened, whole = first[many], np.sort(first[~many])
            if len(opened):
                c = _count(cnt[opened])
                inner = np.arange(c.sum()) - np.repeat(np.cumsum(c) - c, c)
                h, chk = _window_hashes(x, r, np.repeat(lo[opened], c) + inner)
                rows += _windows(h, chk, np.repeat(doc[opened], c), np.repeat(pos[opened], c) + inner, buckets)
                mark = np.unique(trig[opened])
                zero = np.zeros(len(mark), np.uint64)
                rows += _by_bucket(PHRASE, mark, _six(mark), _six(zero), zero.astype(np.int64), zero, zero, buckets)
            rows += _by_bucket(PHRASE, trig[whole], _six(trig[whole]), _six(phr[whole]), doc[whole], pos[whole], cnt[whole], buckets)
            if rows:
                yield _emit(rows)

    return run


def _cols(rows, *names):
    """Concatenated arrays of packed rows."""
    kind = {"doc": "<i8", "pos": "<u4", "chk": np.uint32}
    at = {"doc": 4, "pos": 5, "chk": 3}
    return [np.concatenate([np.frombuffer(r[at[n]], kind[n]) for r in rows]) for n in names]


def _streams(batches):
    """(kind, rows) over sorted batches, for each run of equal (kind, key). Rows that only pass through come TOGETHER, whatever their keys, as a batch
    of each would cost more than the rows; so do buckets of entries: these are told apart by their bytes, and no trigger has two buckets."""
    now, held, size = None, [], 0
    for b in batches:
        for row in zip(*(c.to_pylist() for c in b.columns)):
            kind, full = row[0], size >= TOGETHER
            if held and (kind != now[0] or (full if kind in (SPAN, OPEN) else row[1] != now[1] and (full or kind != ENTRY))):
                yield now[0], held
                held, size = [], 0
            now = row[:2]
            held.append(row)
            size += sum(len(x) for x in row[2:] if x)
    if held:
        yield now[0], held


def _lookup(batches):
    """Dictionary of phrases: spans of those seen before, requests to open first ones that share a trigger. Other kinds pass through."""
    for kind, rows in _streams(batches):
        if kind != PHRASE:
            yield _emit(rows)
            continue
        trig, phr = _unsix([r[2] for r in rows]), _unsix([r[3] for r in rows])
        doc, pos = _cols(rows, "doc", "pos")
        cnt = np.concatenate([np.frombuffer(r[6], "<u2") for r in rows]).astype(np.int64)
        o, new, same = _firsts([trig, phr], doc, pos)
        mark = phr[o] == 0
        later, first = o[~same & ~mark], o[new]
        t = trig[first]
        several, hashed = _of_many(t, 1), _of_many(t, FREQUENT)
        # marks come first among a trigger's entries, so a trigger that has one is told by its first entry
        starts = np.concatenate([[True], t[1:] != t[:-1]])
        hashed |= (phr[first][starts] == 0)[np.cumsum(starts) - 1]
        ask = several & (phr[first] != 0)
        asked, code = first[ask], cnt[first[ask]] | np.where(hashed[ask], _HASHED, 0)
        got = _spans_by_doc(SPAN, doc[later], pos[later], _count(cnt[later])) + _spans_by_doc(OPEN, doc[asked], pos[asked], code)
        if got:
            yield _emit(got)


def _open(buckets):
    """Of the phrases asked for, from (key, base, text, list of pos, list of cnt): their bytes, or their windows where the trigger is frequent."""

    def run(batches):
        held, size = [], 0
        for b in batches:
            off, data, _ = common.byte_views(b.column(2))
            for i, (d, base) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist())):
                text = data[off[i] : off[i + 1]]
                pos, code = _own(b, 3, i, base, len(text))
                ends = np.cumsum(_count(code) + LENGTH - 1)
                cuts = np.searchsorted(ends, np.arange(PIECE, int(ends[-1]) + PIECE, PIECE)) if len(ends) else np.zeros(0, np.int64)
                a = 0
                for z in [*np.unique(cuts).tolist(), len(pos)]:
                    if z > a:
                        length = _count(code[a:z]) + LENGTH - 1
                        held.append((d, base, pos[a:z], code[a:z], text[_ranges(pos[a:z], length)]))
                        size += int(length.sum())
                        a = z
                    if size >= PIECE:
                        yield _flush(held)
                        held, size = [], 0
        if held:
            yield _flush(held)

    def _flush(held):
        code = np.concatenate([h[3] for h in held])
        cnt, place, hashed = _count(code), (code >> _PLACE) & 127, code >= _HASHED
        x = np.concatenate([h[4] for h in held])
        doc = np.concatenate([np.full(len(h[2]), h[0], np.int64) for h in held])
        pos = np.concatenate([h[2] + h[1] for h in held])
        length = cnt + LENGTH - 1
        begin = np.cumsum(length) - length
        r = Rolling(x)
        rows = []
        if hashed.any():
            c = cnt[hashed]
            inner = np.arange(c.sum()) - np.repeat(np.cumsum(c) - c, c)
            h, chk = _window_hashes(x, r, np.repeat(begin[hashed], c) + inner)
            rows += _windows(h, chk, np.repeat(doc[hashed], c), np.repeat(pos[hashed], c) + inner, buckets)
        cold = np.flatnonzero(~hashed)
        if len(cold):
            gram = begin[cold] + place[cold]
            k = (mix(r.of(gram, gram + GRAM)) & np.uint64(buckets - 1)).astype(np.int64)
            o = np.argsort(k, kind="stable")
            k, cold = k[o], cold[o]
            edges = np.concatenate([[0], np.flatnonzero(np.diff(k)) + 1, [len(k)]])
            for i, j in zip(edges[:-1].tolist(), edges[1:].tolist()):
                at = cold[i:j]
                rows.append((ENTRY, int(k[i]), x[_ranges(begin[at], length[at])].tobytes(), None, doc[at].astype("<i8").tobytes(), pos[at].astype("<u4").tobytes(), code[at].astype("<u2").tobytes()))
        return _emit(rows)

    return run


def _ranges(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start[0] ... start[0] + size[0] - 1, start[1] ..., one after another."""
    return np.arange(size.sum()) - np.repeat(np.cumsum(size) - size - start, size)


class _Array:
    """Byte strings (rows of a matrix, padded with zeros, and their lengths) in order, with the lengths that neighbours share."""

    def __init__(self, m: np.ndarray, length: np.ndarray):
        # of strings that differ by trailing zeros alone the shorter comes first, so strings of one beginning lie together
        self.order = np.lexsort((length, np.ascontiguousarray(m).view(f"S{m.shape[1]}").ravel()))
        a, b = m[self.order[:-1]], m[self.order[1:]]
        differ = a != b
        common_ = np.where(differ.any(1), differ.argmax(1), m.shape[1])
        self.shared = np.minimum(common_, np.minimum(length[self.order[:-1]], length[self.order[1:]]))
        #: For each string the most bytes that it shares with any other: that is one of its neighbours.
        self.most = np.zeros(len(m), np.int64)
        self.most[self.order[1:]] = self.shared
        self.most[self.order[:-1]] = np.maximum(self.most[self.order[:-1]], self.shared)

    def runs(self, k: int) -> np.ndarray:
        """For each string the number of its run of strings that share the first k bytes."""
        out = np.empty(len(self.order), np.int64)
        out[self.order] = np.concatenate([[0], np.cumsum(self.shared < k)])
        return out


def repeated_in(x: np.ndarray, code: np.ndarray, doc: np.ndarray, pos: np.ndarray):
    """(doc, first window, number of windows) of the windows that repeat an earlier one among phrases whose bytes follow each other in x."""
    cnt, place = _count(code), (code >> _PLACE) & 127
    o = np.lexsort((pos + place, doc))
    length = cnt + LENGTH - 1
    begin = (np.cumsum(length) - length)[o]
    cnt, place, doc, pos, length = cnt[o], place[o], doc[o], pos[o], length[o]
    n, gram, end = len(cnt), begin + place, begin + length
    after = gram[:, None] + np.arange(LENGTH)
    right = _Array(np.where(after < end[:, None], x[np.minimum(after, len(x) - 1)], np.uint8(0)), np.minimum(length - place, LENGTH))
    most = LENGTH - GRAM
    before = gram[:, None] - 1 - np.arange(most)
    left = _Array(np.where(before >= begin[:, None], x[np.maximum(before, 0)], np.uint8(0)), place)
    found = np.zeros((n, most + 3), bool)  # a column for each window of a phrase, with an empty one at either end
    # a window with k bytes before the trigger has an equal one only if its phrase shares so many bytes on either side
    low, high = np.maximum(LENGTH - right.most, place - cnt + 1), np.minimum(left.most, place)
    for k in range(max(0, int(low.min())), int(high.max()) + 1):
        rows = np.flatnonzero((low <= k) & (k <= high))
        if len(rows) < 2:
            continue
        _, first, run = np.unique(right.runs(LENGTH - k)[rows] * n + left.runs(k)[rows], return_index=True, return_inverse=True)
        head = rows[first[run]]
        later = rows[(doc[rows] != doc[head]) | ((pos + place)[rows] != (pos + place)[head])]
        found[later, place[later] - k + 1] = True
    step = np.diff(found.astype(np.int8), axis=1)
    (row, a), (_, z) = np.nonzero(step == 1), np.nonzero(step == -1)
    return doc[row], pos[row] + a, z - a


def _suffixes(batches):
    """Repeated windows, from the bytes of dictionary phrases or from hashed windows."""
    for kind, rows in _streams(batches):
        if kind == ENTRY:
            code = np.concatenate([np.frombuffer(r[6], "<u2") for r in rows]).astype(np.int64)
            doc, pos = _cols(rows, "doc", "pos")
            got = _spans_by_doc(SPAN, *repeated_in(np.concatenate([np.frombuffer(r[2], np.uint8) for r in rows]), code, doc, pos.astype(np.int64)))
        elif kind == WINDOW:
            h = _unsix([r[2] for r in rows])
            chk, doc, pos = _cols(rows, "chk", "doc", "pos")
            later = _first_windows(h, chk, doc, pos)[1]
            got = _spans_by_doc(SPAN, doc[later], pos[later], np.ones(len(later)))
        else:
            got = rows
        if got:
            yield _emit(got)


def _own(b, at: int, i: int, base: int, size: int, coded: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """Of a document's packed places and counts (columns at, at + 1) those in the part of ``size`` bytes that starts at ``base``, from its start."""
    pos, cnt = (np.concatenate([np.frombuffer(x, "<u4") for x in b.column(c)[i].as_py()]).astype(np.int64) for c in (at, at + 1))
    pos = pos - base
    fit = (pos >= 0) & (pos + (_count(cnt) if coded else cnt) + LENGTH - 1 <= size)
    return pos[fit], cnt[fit]


def removed_runs(n: int, pos: np.ndarray, cnt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs [from, to) covered by ``cnt`` windows each, starting at ``pos``, in a text of n bytes."""
    if not len(pos):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    o = np.argsort(pos, kind="stable")
    lo, hi = pos[o], np.minimum(np.maximum.accumulate((pos + cnt + LENGTH - 1)[o]), n)
    new = np.concatenate([[True], lo[1:] > hi[:-1]])
    a, z = lo[new], np.concatenate([hi[np.flatnonzero(new)[1:] - 1], hi[-1:]])
    ok = a < z
    return a[ok], z[ok]


def _cut(batches):
    for b in batches:
        off, data, _ = common.byte_views(b.column(2))
        out = []
        for i, (d, base) in enumerate(zip(b.column(0).to_pylist(), b.column(1).to_pylist())):
            text = data[off[i] : off[i + 1]]
            a = z = np.zeros(0, np.int64)
            if b.column(3)[i].is_valid:
                a, z = removed_runs(len(text), *_own(b, 3, i, base, len(text), False))
            sha, at = hashlib.sha256(), 0
            for x, y in zip(a.tolist(), z.tolist()):
                sha.update(text[at:x])
                at = y
            sha.update(text[at:])
            out.append((d, len(text), int((z - a).sum()), len(a), sha.hexdigest()))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*out), (pa.int64(),) * 4 + (pa.string(),))], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def _spans_of(df: DataFrame, kind: int) -> DataFrame:
    return df.where(F.col("kind") == kind).groupBy(F.col("key").alias("at")).agg(F.collect_list("pos").alias("pos"), F.collect_list("cnt").alias("cnt"))


def _placed(src: DataFrame) -> DataFrame:
    """(doc_id, text) with the document ``at`` and the place ``base`` where the text begins in it: the id and 0, but for texts without an id and different
    texts of one id. These are found by a narrow aggregate; where there are none, nothing is joined."""
    h = F.xxhash64("text")
    at = F.coalesce("doc_id", h)
    several = src.where("doc_id is not null").groupBy("doc_id").agg(F.min(h).alias("a"), F.max(h).alias("z")).where("a <> z").select("doc_id")
    several = materialise(several, "shared-ids")
    if several.isEmpty():
        return src.select("doc_id", at.alias("at"), F.lit(0).cast("long").alias("base"), "text")
    parts = src.join(several, "doc_id", "left_semi").select("doc_id", h.alias("h"), F.octet_length("text").cast("long").alias("size")).distinct()
    before = F.sum(F.col("size") + GAP).over(Window.partitionBy("doc_id").orderBy("h").rowsBetween(Window.unboundedPreceding, -1))
    parts = materialise(parts.withColumn("base", F.coalesce(before, F.lit(0).cast("long"))).select("doc_id", "h", "base", (F.col("base") + F.col("size") < PLACES).alias("fits")), "parts")
    j = src.withColumn("h", h).join(parts, ["doc_id", "h"], "left")
    # parts beyond the places of one document become documents of their own
    own = F.coalesce("fits", F.lit(True))
    return j.select("doc_id", F.when(own, at).otherwise(F.xxhash64("doc_id", "h")).alias("at"), F.when(own, F.coalesce("base", F.lit(0).cast("long"))).otherwise(F.lit(0).cast("long")).alias("base"), "text")


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(documents with their repeated windows, the same as spans): spans are lists of packed first windows and numbers of windows."""
    prepare(docs.sparkSession)
    src = _placed(docs.select(docs[id_col].cast("long").alias("doc_id"), F.coalesce(docs[text_col].cast("string"), F.lit("")).alias("text")))
    buckets = common.bucket_count(src, least=256)

    def dealt(df):
        return df.repartition("kind", "key").sortWithinPartitions("kind", "key")

    parsed = src.where(F.octet_length("text") >= LENGTH).select("at", "base", "text").mapInArrow(lean(_parse(buckets)), ROWS_DDL)
    looked = materialise(dealt(parsed).mapInArrow(lean(_lookup), ROWS_DDL), "phrases")
    asked = src.join(_spans_of(looked, OPEN), "at").select("at", "base", "text", "pos", "cnt")
    # spans that are known need no bucket
    opened = looked.where(~F.col("kind").isin(OPEN, SPAN)).unionByName(asked.mapInArrow(lean(_open(buckets)), ROWS_DDL))
    found = materialise(dealt(opened).mapInArrow(lean(_suffixes), ROWS_DDL).unionByName(looked.where(F.col("kind") == SPAN)), "spans")
    discard(looked)
    return src.join(_spans_of(found, SPAN), "at", "left").select("doc_id", "base", "text", "pos", "cnt"), found


def deduplicated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return repeats(docs, id_col, text_col)[0].mapInArrow(lean(_cut), OUT)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicated(table(spark, sf_dir, "documents"))
