"""N-gram Jaccard join with set-relation skipping.

Words of every whole text become a set of shingle hashes; two texts link when ``den * |A n B| >= num * |A u B|``. The join is exact.

1. *Signing*: one map-only pass gives each document its set size and a 64-bit set id; equal sets share the id, so exact copies
   collapse before any join. The same pass counts the shingles of the low third of the hash range over all documents.
2. *Index*: shingles are ordered (frequent last, then by hash). By the prefix principle two linked sets share a shingle among their
   first ``floor(n * (den - num) / den) + 1``; only these are shuffled, as packed lists by hash bucket. Each index list is ordered by size, then by
   the position of the shingle in its set, so sets of one size form a block whose positions ascend. A set that has the shingle at position i can only
   link to those of a block whose position lies in one interval around i (:func:`_open`); what lies outside is skipped without being looked at.
   Lists with the same members collapse to one; long lists are cut into rows of ``BLOCK`` sets. The same pass and shuffle carry a quarter of each
   distinct set (by hash range), once each.
3. *Answers of one set per list*: the set of a list that holds most frequent shingles is verified against each other member: linear in the list, however
   long it is. Links so found give first components.
   Verification reads a quarter of each set first, and whole sets only where the quarters leave a link possible; whole sets are made again from the
   texts that have them.
4. *Answers derived incrementally*: other pairs of a list matter only between components. The known overlaps with the list's first
   set bound the overlap of any two others from both sides: pairs certain to link or certain not to are decided without reading
   sets; position blocks and size bounds skip others; what is left is verified exactly.

Sizes sent to all tasks: the frequent shingles, at most ``HOT_CAP``, and ids of documents whose whole sets are wanted, at most ``SENT``; where there are
more, texts and ids meet in a merge join. Lists of frequent shingles stay whole: they come last in the
order. Long lists (``MANY`` sets or more) of one first set are compared as one group, block against block over many tasks: certain links first, then
matrix products that give all overlaps of two blocks for the sets that still have an open pair; only links that join components leave.
Joins on a component or a set keep one narrow row a distinct text, which the runtime's skew handling splits.

Null text, empty text and text without words have the empty set: size 0, linked with nothing. A null id gives a row with a null
component. Rows that share an id count as one document: their sets belong to one component (a row without words keeps its own id).
Other columns are not read. An empty table gives an empty result.
Set ids and shingles are 64-bit hashes: for n distinct sets or shingles a clash has probability n * n / 2 ** 65.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.llm import common
from elastipool.llm.common import WordHashes, components, discard, lean, materialise, prepare, shingles, table

#: Most frequent shingles sent to all tasks (8 bytes each), least count of a frequent one, block of a list, words packed at once.
HOT_CAP, HOT_LEAST, BLOCK, FLUSH = 1 << 20, 16, 2048, 1 << 20
#: Lists of so many sets are compared as whole groups, in blocks of so many sets; columns of a block's matrix.
MANY, SETS, COLUMNS = 32, 512, 4096
#: Most ids of documents sent to all tasks (16 bytes each).
SENT = 1 << 20
LOW, QUARTER = np.uint64((1 << 64) // 3), np.uint64(1 << 62)
SIGN = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("sid", pa.int64()), ("bucket", pa.int32()), ("low", pa.binary())])
QUARTERS = [("own", pa.int64()), ("size", pa.int64()), ("items", pa.binary())]
PACK = pa.schema([("bucket", pa.int32()), ("data", pa.binary()), *QUARTERS])
PACK_DDL = "bucket int, data binary, own long, size long, items binary"
LISTS = pa.schema([("gid", pa.int64()), ("m", pa.int64()), ("sid", pa.list_(pa.int64())), ("n", pa.list_(pa.int32())), ("pos", pa.list_(pa.int32())), *QUARTERS])
LISTS_DDL = "gid long, m long, sid array<long>, n array<int>, pos array<int>, own long, size long, items binary"
ENTRY = np.dtype([("t", "<u8"), ("sid", "<i8"), ("n", "<u4"), ("pos", "<u4"), ("pop", "<u2")])


def needed(n, num: int, den: int):
    """Least overlap of a set of n with any set it links to."""
    return (n * num + den - 1) // den


def pair_overlap(n, m, num: int, den: int):
    """Least overlap of linked sets of n and m: den * o >= num * (n + m - o)."""
    return (num * (n + m) + num + den - 1) // (num + den)


def set_id(s: np.ndarray) -> int:
    return int(np.int64(np.uint64(xxhash.xxh3_64_intdigest(s.tobytes()))))


def batch_sets(batches, width, known=None):
    """(doc id, sorted distinct shingle hashes) of every row of (doc_id, text) batches."""
    known = WordHashes() if known is None else known
    for b in batches:
        ids = b.column(0).to_pylist()
        for i, t in zip(ids, common.pairs_of(b, "text")):
            yield i, shingles(common.word_hashes(t, known), width) if t else np.zeros(0, np.uint64)


def _by_bucket(keys: np.ndarray, buckets: int):
    """Slices of equal bucket (low bits of the keys): (bucket, order slice)."""
    b = (keys & np.uint64(buckets - 1)).astype(np.int64)
    order = np.argsort(b, kind="stable")
    b = b[order]
    cuts = np.flatnonzero(np.diff(b)) + 1
    for part in np.split(order, cuts):
        if len(part):
            yield int(keys[part[0]] & np.uint64(buckets - 1)), part


def _signer(width, buckets):
    def run(batches):
        held, size, rows = [], 0, []

        def flush():
            low = np.concatenate(held) if held else np.zeros(0, np.uint64)
            got = rows + [(None, None, None, b, np.sort(low[p]).tobytes()) for b, p in _by_bucket(low, buckets)]
            return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*got), SIGN)], schema=SIGN)

        for i, s in batch_sets(batches, width):
            rows.append((i, len(s), set_id(s) if len(s) else None, -1 - len(rows) % buckets, None))
            held.append(s[: np.searchsorted(s, LOW)])
            size += len(held[-1]) + 1
            if size >= FLUSH:
                yield flush()
                held, size, rows = [], 0, []
        if rows:
            yield flush()

    return run


def _grouped(batches, key: str):
    """Runs of equal key over sorted batches: (key, list of the other column's values)."""
    now, held = None, []
    for b in batches:
        for k, v in zip(b.column(0).to_pylist(), b.column(1)):
            if k != now and held:
                yield now, held
                held = []
            now = k
            held.append(v.as_buffer())
    if held:
        yield now, held


def _count(batches):
    """Counts of the packed shingles, as (t, c); the rows of documents (negative buckets) pass through."""
    out = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("sid", pa.int64()), ("t", pa.int64()), ("c", pa.int64())])

    def lists():
        for b in batches:
            own = np.asarray(b.column(3)) < 0
            if own.any():
                rows = b.filter(pa.array(own))
                none = pa.nulls(rows.num_rows, pa.int64())
                passed.append(pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), rows.column(2), none, none], schema=out))
            if not own.all():
                yield b.filter(pa.array(~own)).select(["bucket", "low"])

    passed: list[pa.RecordBatch] = []
    for _, blobs in _grouped(lists(), "bucket"):
        yield from passed
        passed.clear()
        t, c = np.unique(np.concatenate([np.frombuffer(x, np.uint64) for x in blobs]), return_counts=True)
        keep = c >= HOT_LEAST
        if keep.any():
            none = pa.nulls(int(keep.sum()), pa.int64())
            yield pa.RecordBatch.from_arrays([none, none, none, pa.array(t[keep].view(np.int64)), pa.array(c[keep].astype(np.int64))], schema=out)
    yield from passed


def _packer(width, num, den, hot, buckets):
    def run(batches):
        frequent, known, size, held, quarters = hot.value, set(), 0, [], []

        def flush():
            e = np.concatenate(held)
            rows = [(b, e[p].tobytes(), None, None, None) for b, p in _by_bucket(e["t"], buckets)] + quarters
            return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), PACK)], schema=PACK)

        for _, s in batch_sets(batches, width):
            n = len(s)
            if not n or (sid := set_id(s)) in known:
                continue
            known.add(sid)
            quarters.append((sid & (buckets - 1), None, sid, n, s[: np.searchsorted(s, QUARTER)].tobytes()))
            p = n - needed(n, num, den) + 1
            pop = 0
            if len(frequent):
                at = np.minimum(np.searchsorted(frequent, s), len(frequent) - 1)
                is_hot = frequent[at] == s
                pop = 65535 * int(is_hot.sum()) // max(1, int(np.searchsorted(s, LOW)))
                s = np.concatenate([s[~is_hot][:p], s[is_hot][: max(0, p - (n - int(is_hot.sum())))]])
            e = np.empty(min(p, len(s)), ENTRY)
            e["t"], e["sid"], e["n"], e["pos"], e["pop"] = s[:p], sid, n, np.arange(len(e)), pop
            held.append(e)
            size += len(e)
            if size >= FLUSH // 2:
                yield flush()
                held, quarters, size, known = [], [], 0, set()
        if held:
            yield flush()

    return run


def _lists(batches):
    """Index lists of at least two sets, first set first, the rest by size and position; lists of the same members collapse within a task.
    Quarters of sets pass through, once each: equal sets share a bucket, and buckets come in order."""
    passed: list[pa.RecordBatch] = []
    known: set[int] = set()
    at = None

    def packed():
        nonlocal at
        for b in batches:
            own = np.asarray(b.column("own").is_valid())
            if own.any():
                rows = b.filter(pa.array(own))
                first = []
                for bucket, sid in zip(rows.column("bucket").to_pylist(), rows.column("own").to_pylist()):
                    if bucket != at:
                        known.clear()
                        at = bucket
                    first.append(sid not in known)
                    known.add(sid)
                rows = rows.filter(pa.array(first))
                none = [pa.nulls(rows.num_rows, f.type) for f in LISTS][:5]
                passed.append(pa.RecordBatch.from_arrays([*none, *(rows.column(f[0]) for f in QUARTERS)], schema=LISTS))
            if not own.all():
                yield b.filter(pa.array(~own)).select(["bucket", "data"])

    seen: set[int] = set()
    for _, blobs in _grouped(packed(), "bucket"):
        yield from passed
        passed.clear()
        e = np.concatenate([np.frombuffer(x, ENTRY) for x in blobs])
        e = e[np.lexsort((e["sid"], e["t"]))]
        fresh = np.ones(len(e), bool)
        fresh[1:] = (e["t"][1:] != e["t"][:-1]) | (e["sid"][1:] != e["sid"][:-1])
        e = e[fresh]
        starts = np.flatnonzero(np.concatenate([[True], e["t"][1:] != e["t"][:-1]]))
        ends = np.concatenate([starts[1:], [len(e)]])
        rows = []
        for a, z in zip(starts[(ends - starts) > 1].tolist(), ends[(ends - starts) > 1].tolist()):
            gid = xxhash.xxh3_64_intdigest(e["sid"][a:z].tobytes())
            if gid in seen:
                continue
            if len(seen) > 500_000:
                seen.clear()
            seen.add(gid)
            g = int(np.int64(np.uint64(gid)))
            one = e[a:z]
            # the list's first set is its most common one: an original shares more with its near copies than they do with each other
            lead = int(np.argmax(one["pop"]))
            others = np.lexsort((one["sid"], one["pos"], one["n"]))
            others = others[others != lead]
            for i in range(0, len(others), BLOCK):
                # every row leads with the first set, which is verified against all others
                part = one[np.concatenate([[lead], others[i : i + BLOCK]])]
                rows.append((g, z - a, part["sid"], part["n"].astype(np.int32), part["pos"].astype(np.int32), None, None, None))
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*rows), LISTS)], schema=LISTS)
    yield from passed


class _Blocks:
    """A list ordered by (size, position): its blocks of one size, and where each block's open positions begin and end for a given set."""

    def __init__(self, n: np.ndarray, pos: np.ndarray, num: int, den: int):
        self.key = (n << np.int64(32)) | pos
        self.sizes = np.unique(n)
        self.num, self.den = num, den

    def open(self, n: int, i: int) -> np.ndarray:
        """Places of the sets that a set of ``n`` with the list's shingle at ``i`` may link to. With the shingle at j of a set of m, at most
        min(i, j) + 1 + min(n - i - 1, m - j - 1) can be shared, so j lies between i - (n - need) and i + (m - need)."""
        a, z = np.searchsorted(self.sizes, [needed(n, self.num, self.den), n * self.den // self.num + 1])
        m = self.sizes[a:z]
        need = pair_overlap(n, m, self.num, self.den)
        fits = np.minimum(n, m) >= need
        m, need = m[fits], need[fits]
        low = np.searchsorted(self.key, (m << np.int64(32)) | np.maximum(i - (n - need), 0))
        high = np.searchsorted(self.key, (m << np.int64(32)) | (i + m - need), "right")
        kept = high > low
        return np.concatenate([np.arange(x, y) for x, y in zip(low[kept], high[kept])]) if kept.any() else np.zeros(0, np.int64)


def _may_link(n, m, i, j, num, den):
    """Size and position bounds of pairs that share the shingle at positions i and j."""
    need = pair_overlap(n, m, num, den)
    most = np.minimum(i, j) + 1 + np.minimum(n - i - 1, m - j - 1)
    return (np.minimum(n, m) >= need) & (most >= need)


def _first_pairs(num, den):
    out = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches):
        for b in batches:
            xs, ys, size = [], [], 0
            for k, (sid, n, pos) in enumerate(zip(b.column(0), b.column(1), b.column(2))):
                sid, n, pos = (np.asarray(x.values).astype(np.int64) for x in (sid, n, pos))
                at = _Blocks(n[1:], pos[1:], num, den).open(int(n[0]), int(pos[0]))
                ys.append(sid[1:][at])
                xs.append(np.full(len(at), sid[0]))
                size += len(at)
                if size >= FLUSH >> 2 or k + 1 == b.num_rows:
                    p = np.unique(np.stack([np.concatenate(xs), np.concatenate(ys)], 1), axis=0)
                    yield pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1])], schema=out)
                    xs, ys, size = [], [], 0

    return run


def _set_rows(width):
    """(sid, n, items) of (doc_id, text, want) rows whose set is the one wanted. Repeated rows come once."""
    out = pa.schema([("sid", pa.int64()), ("n", pa.int64()), ("items", pa.binary())])

    def run(batches):
        seen: set[int] = set()
        known = WordHashes()
        for b in batches:
            got = []
            for (_, s), want in zip(batch_sets([b], width, known), b.column(2).to_pylist()):
                if len(s) and want not in seen and set_id(s) == want:
                    seen.add(want)
                    got.append((want, len(s), s.tobytes()))
            if got:
                yield pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(zip(*got), out)], schema=out)

    return run


BOUNDS = pa.schema([(c, pa.int64()) for c in ("a", "b", "n", "m", "lo", "hi")])
BOUNDS_DDL = "a long, b long, n long, m long, lo long, hi long"


def _overlaps(whole: bool):
    """Bounds of the overlaps of (a, b, x, y, n, m): exact from whole sets; from quarters, the rest may match as far as the sizes allow."""

    def run(batches):
        for b in batches:
            n, m = np.asarray(b.column(4)), np.asarray(b.column(5))
            lo, free = np.zeros(b.num_rows, np.int64), np.zeros(b.num_rows, np.int64)
            for k, (x, y) in enumerate(zip(b.column(2), b.column(3))):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                free[k] = 0 if whole else min(n[k] - len(x), m[k] - len(y))
                x, y = (x, y) if len(x) >= len(y) else (y, x)
                if len(y):
                    lo[k] = (x[np.minimum(np.searchsorted(x, y), len(x) - 1)] == y).sum()
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n), pa.array(m), pa.array(lo), pa.array(lo + free)], schema=BOUNDS)

    return run


def _bounded(pairs: DataFrame, sets: DataFrame, whole: bool) -> DataFrame:
    """Bounds lo <= overlap <= hi of pairs(a, b) of set ids, from tables of whole sets or of their quarters."""
    left = sets.select(F.col("sid").alias("b"), F.col("n").alias("m"), F.col("items").alias("y"))
    right = sets.select(F.col("sid").alias("a"), "n", F.col("items").alias("x"))
    # merge joins at any size: what is shuffled grows with the input, without a step where a side outgrows a broadcast
    return pairs.hint("merge").join(left, "b").hint("merge").join(right, "a").select("a", "b", "x", "y", "n", "m").mapInArrow(lean(_overlaps(whole)), BOUNDS_DDL)


def _parts(a: np.ndarray, size: int):
    return (a[k : k + size] for k in range(0, len(a), size))


def _rest(num, den):
    """Pairs of lists (np, members) of fewer than ``MANY`` sets that lie in different components: decided by the overlaps with the list's
    first set, or left. Lists of one length are looked at together."""
    out = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("sure", pa.bool_())])

    def run(batches):
        for b in batches:
            first, col = np.asarray(b.column(0)), b.column(1)
            off = np.asarray(col.offsets)
            size, flat = np.diff(off), {f: np.asarray(col.values.field(f)) for f in ("sid", "n", "pos", "comp", "lo", "hi")}
            got = []
            # so many lists at once that their pairs are few enough for small arrays
            for m, rows in ((m, part) for m in np.unique(size[size > 1]) for part in _parts(np.flatnonzero(size == m), (1 << 18) // int(m * m) + 1)):
                sid, n, pos, comp, lo, hi = (flat[f][off[rows][:, None] + np.arange(m)] for f in ("sid", "n", "pos", "comp", "lo", "hi"))
                x, y = np.triu_indices(int(m), 1)
                need = pair_overlap(n[:, x], n[:, y], num, den)
                open_ = (comp[:, x] != comp[:, y]) & _may_link(n[:, x], n[:, y], pos[:, x], pos[:, y], num, den)
                open_ &= np.minimum(hi[:, x], hi[:, y]) + np.minimum(n[:, x] - lo[:, x], n[:, y] - lo[:, y]) >= need
                sure = open_ & (lo[:, x] + lo[:, y] - first[rows][:, None] >= need)
                # a certain link joins two components, so other pairs of the two are not needed
                tied = set(zip(*(v[sure].tolist() for v in (np.minimum(comp[:, x], comp[:, y]), np.maximum(comp[:, x], comp[:, y])))))
                if tied:
                    r, c = np.nonzero(open_ & ~sure)
                    u, v = comp[r, x[c]], comp[r, y[c]]
                    known = np.array([(min(p), max(p)) in tied for p in zip(u.tolist(), v.tolist())], bool)
                    open_[r[known], c[known]] = False
                u, v, w = sid[:, x][open_], sid[:, y][open_], sure[open_]
                got.append(np.stack([np.minimum(u, v), np.maximum(u, v), w.astype(np.int64)], 1))
            p = np.unique(np.concatenate(got), axis=0) if got else np.zeros((0, 3), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(p[:, 0]), pa.array(p[:, 1]), pa.array(p[:, 2] == 1)], schema=out)

    return run


def _dense(num, den):
    """Links between components among the sets of a block (or across two blocks), from all overlaps at once: products of 0/1 matrices over
    the shingles that at least two of the sets hold. Only as many links leave as join components."""
    out = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("sure", pa.bool_())])

    def run(_, t):
        sid, n, lo, hi, np_, half = (np.asarray(t.column(c)) for c in ("sid", "n", "lo", "hi", "np", "half"))
        comp = np.unique(np.asarray(t.column("comp")), return_inverse=True)[1]
        need = pair_overlap(n[:, None], n[None, :], num, den)
        most = np.minimum(hi[:, None], hi[None, :]) + np.minimum((n - lo)[:, None], (n - lo)[None, :])
        open_ = (np.minimum(n[:, None], n[None, :]) >= need) & (most >= need)
        if not (half == 2).all():
            open_ &= half[:, None] != half[None, :]
        ties = []

        def join(link):
            """One pair for each two components that the links join."""
            for i, j in zip(*np.nonzero(link & (comp[:, None] != comp[None, :]))):
                if comp[i] != comp[j]:
                    comp[comp == comp[j]] = comp[i]
                    ties.append((sid[i], sid[j]))

        # two sets that share much with the first set share much with each other: certain links need no items
        join(open_ & (lo[:, None] + lo[None, :] - np_[0] >= need))
        open_ &= comp[:, None] != comp[None, :]
        live = open_.any(1)
        if live.any():
            at = np.flatnonzero(live)
            sets = [np.frombuffer(t.column("items")[int(k)].as_py(), np.uint64) for k in at]
            token, col, times = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
            row = np.repeat(np.arange(len(at)), [len(x) for x in sets])
            shared = times[col] > 1
            col, row = (np.cumsum(times > 1) - 1)[col[shared]], row[shared]
            o = np.argsort(col, kind="stable")
            col, row = col[o], row[o]
            got = np.zeros((len(at), len(at)), np.float32)
            for c in range(0, int(col[-1]) + 1 if len(col) else 0, COLUMNS):
                i, j = np.searchsorted(col, [c, c + COLUMNS])
                x = np.zeros((len(at), COLUMNS), np.float32)
                x[row[i:j], col[i:j] - c] = 1
                got += x @ x.T
            link = np.zeros_like(open_)
            link[np.ix_(at, at)] = got >= need[np.ix_(at, at)]
            join(link & open_)
        return pa.table([pa.array([min(x) for x in ties], pa.int64()), pa.array([max(x) for x in ties], pa.int64()), pa.array([True] * len(ties))], schema=out)

    return run


def linked(width: int, num: int, den: int, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of ``docs``."""
    spark = docs.sparkSession
    prepare(spark)
    src = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))
    buckets = common.bucket_count(src, least=256)
    # one shuffle carries both the rows of documents and the packed shingles to be counted; nothing packed is written
    signed = src.mapInArrow(lean(_signer(width, buckets)), "doc_id long, n long, sid long, bucket int, low binary").repartition("bucket").sortWithinPartitions("bucket")
    signed = materialise(signed.mapInArrow(lean(_count), "doc_id long, n long, sid long, t long, c long"), "signed")
    sigs, counts = signed.where("c is null").select("doc_id", "n", "sid"), signed.where("c is not null").select("t", "c")
    bins = {r.k: r.n for r in counts.groupBy(F.floor(F.log2("c")).cast("int").alias("k")).agg(F.count("*").alias("n")).collect()}
    floor_ = next(k for k in range(64) if sum(n for b, n in bins.items() if b >= k) <= HOT_CAP)
    hot = np.sort(np.asarray(counts.where(F.col("c") >= F.lit(1 << floor_)).select("t").toArrow().column(0), np.int64).view(np.uint64))
    hot = spark.sparkContext.broadcast(hot)

    packed = src.mapInArrow(lean(_packer(width, num, den, hot, buckets)), PACK_DDL).repartition("bucket").sortWithinPartitions("bucket")
    made = materialise(packed.mapInArrow(lean(_lists), LISTS_DDL), "lists", "snappy")
    lists = made.where("gid is not null").select("gid", "m", "sid", "n", "pos")
    quarters = made.where("own is not null").select(F.col("own").alias("sid"), F.col("size").alias("n"), "items")

    first = materialise(lists.select("sid", "n", "pos").mapInArrow(lean(_first_pairs(num, den)), "a long, b long").distinct(), "first")
    reps = sigs.where("sid is not null and doc_id is not null").groupBy("sid").agg(F.min("doc_id").alias("rep"))

    def sets_of(sids: DataFrame) -> DataFrame:
        """Sets by id, made again from the texts that have them; these stay where they are as long as there are ``SENT`` ids at most."""
        chosen = reps.join(sids.distinct(), "sid").select(F.col("rep").alias("doc_id"), F.col("sid").alias("want"))
        chosen = materialise(chosen, "chosen")
        chosen = chosen.hint("broadcast" if chosen.count() <= SENT else "merge")
        return materialise(src.join(chosen, "doc_id").select("doc_id", "text", "want").mapInArrow(lean(_set_rows(width)), "sid long, n long, items binary"), "sets", "snappy")

    ends = lambda pairs: pairs.select(F.explode(F.array("a", "b")).alias("sid"))
    may = (F.col("hi") * den) >= (F.col("n") + F.col("m") - F.col("hi")) * num
    link = (F.col("lo") * den) >= (F.col("n") + F.col("m") - F.col("lo")) * num
    rough = materialise(_bounded(first, quarters, False), "rough")
    near = rough.where(may).select("a", "b")
    sets = sets_of(ends(near).union(lists.where(F.col("m") >= MANY).select(F.explode("sid"))))
    known = materialise(rough.where(~may).unionByName(_bounded(near, sets, True)), "known")
    links = known.where(link).select("a", "b")
    comp = components(links)

    def members(df: DataFrame, *cols: str) -> DataFrame:
        """The sets of lists but their first, with the component of each."""
        e = df.select("gid", F.col("sid")[0].alias("a"), F.col("n")[0].cast("long").alias("np"), F.posexplode(F.arrays_zip("sid", "n", "pos")).alias("k", "e")).where("k > 0")
        e = e.select("gid", "a", "np", F.col("e.sid").alias("sid"), F.col("e.n").cast("long").alias("n"), F.col("e.pos").cast("long").alias("pos")).select(*cols)
        e = e if "gid" in cols else e.distinct()
        return e.join(comp.withColumnRenamed("node", "sid"), "sid", "left").withColumn("comp", F.coalesce("root", "sid")).drop("root")

    # any two members of a list may meet, whatever their pairs with the first set said; a short list is one row, and equal lists count once
    few = members(lists.where((F.col("m") > 2) & (F.col("m") < MANY)).dropDuplicates(["gid"]), "gid", "a", "np", "sid", "n", "pos")
    mixed = few.groupBy("gid").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("gid")
    bounds = known.select("a", F.col("b").alias("sid"), "lo", "hi")
    # of a member that the size or position bound kept from its first set only the trivial bounds are known
    bounded = lambda df: df.join(bounds, ["a", "sid"], "left").withColumn("lo", F.coalesce("lo", F.lit(0).cast("long"))).withColumn("hi", F.coalesce("hi", "n"))
    # narrow rows, but much work on each: partitions by number are not merged to fewer tasks
    whole = bounded(few.join(mixed, "gid")).repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "gid")
    whole = whole.groupBy("gid").agg(F.first("np").alias("np"), F.collect_list(F.struct("sid", "n", "pos", "comp", "lo", "hi")).alias("of"))
    more = whole.select("np", "of").mapInArrow(lean(_rest(num, den)), "a long, b long, sure boolean")

    # long lists of one first set are taken together, so that a pair is looked at once and not in each of them
    group = members(lists.where(F.col("m") >= MANY), "a", "np", "sid", "n")
    size = group.groupBy("a").agg(F.count("*").alias("m"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("a", F.ceil(F.col("m") / SETS).cast("int").alias("blocks"))
    group = bounded(group.join(size, "a")).join(sets.select("sid", "items"), "sid")
    group = group.withColumn("block", F.pmod(F.xxhash64("sid"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    half = F.when(F.col("block") == F.col("other"), 2).when(F.col("block") < F.col("other"), 0).otherwise(1)
    group = group.select("a", F.least("block", "other").alias("b1"), F.greatest("block", "other").alias("b2"), half.alias("half"), "sid", "n", "comp", "lo", "hi", "np", "items")
    more = more.unionByName(group.groupBy("a", "b1", "b2").applyInArrow(_dense(num, den), "a long, b long, sure boolean"))
    more = materialise(more.groupBy("a", "b").agg(F.max("sure").alias("sure")), "rest")
    left = more.where("not sure").select("a", "b")
    rough_late = materialise(_bounded(left, quarters, False), "rough")
    near_late = rough_late.where(may).select("a", "b")
    missing = materialise(ends(near_late).distinct().join(sets.select("sid"), "sid", "left_anti"), "missing")
    every = sets if missing.isEmpty() else sets.unionByName(sets_of(missing))
    late = materialise(_bounded(near_late, every, True), "late")
    # rows that share an id are one document, so their sets belong together
    of_id = sigs.where("sid is not null and doc_id is not null").groupBy("doc_id").agg(F.min("sid").alias("a"), F.max("sid").alias("z")).where("a <> z").select("doc_id", "a")
    same_id = sigs.join(of_id, "doc_id").where("sid <> a").select("a", F.col("sid").alias("b"))
    all_links = links.union(more.where("sure").select("a", "b")).union(late.where(link).select("a", "b")).union(same_id)
    comp = components(all_links)

    by_sid = reps.join(comp.withColumnRenamed("node", "sid"), "sid", "left").withColumn("root", F.coalesce("root", "sid"))
    low = by_sid.groupBy("root").agg(F.min("rep").alias("component_id"))
    by_sid = materialise(by_sid.join(low, "root").select("sid", "component_id"), "classes")
    sids = sigs.join(by_sid, "sid", "left")
    out = sids.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNull(), F.lit(None).cast("long")).otherwise(F.coalesce("component_id", "doc_id")).alias("component_id"))
    for t in (made, first, rough, sets, known, more, rough_late, missing, late):
        discard(t)
    return out


def components_of(docs: DataFrame, width: int = 5, num: int = 75, den: int = 100) -> DataFrame:
    return linked(width, num, den, docs)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return components_of(table(spark, sf_dir, "documents"))

