"""Toxicity of texts behind a noisy channel.

*Restoring.* Words written in leetspeak (digits and signs for letters), spaced out letter by letter, or with letters repeated are taken as the output
of a noisy channel. Each becomes a character lattice (the letters a sign may stand for; a run kept once, twice or as it is; spaces between
single letters dropped, or kept as word borders); a Viterbi search finds the path of least channel cost plus cost under a character trigram model, whose counts
come from the words of all documents. Tokens of any length are searched. A phrase spaced out as a whole is parted into words by the counts of the
corpus' ``WORDS`` most frequent words. Words of letters alone pass unchanged, so clean texts are left as they are.

*Scoring.* Words of the restored text, and their beginnings of 3 to 6 bytes, are presence features. Features come from a bounded sample of
labelled rows, at most ``SAMPLE``, by their G statistic; a logistic regression over the ``FEATURES`` strongest is trained on the same rows and scores every whole text.

Null and empty texts, and texts without a known feature, get the score of the intercept. Rows without a label or id are scored and never learned from;
a doc_id labelled more than once counts by its highest label. With nothing to learn every score is 0. Repeated rows score alike; other
columns are never inputs; empty tables give an empty result.
"""

from __future__ import annotations

import math
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from elastipool.llm import common
from elastipool.llm.common import lean, prepare, table
from elastipool.llm.langid import fold

#: Labelled rows learned from, features kept, least G, prefix lengths in bytes.
SAMPLE, FEATURES, LEAST_G, PREFIXES = 12_000, 4096, 16.0, (3, 4, 5, 6)
OUT = "doc_id long, held_out boolean, score double, predicted int"

#: What a sign may stand for.
LEET = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "€": "e", "*": "aeiou", "(": "c", "#": "h",
}
_SIGNS = re.escape("".join(LEET))
_WORD = re.compile(rf"[^\W\d_][\w{_SIGNS}]*[{_SIGNS}][\w{_SIGNS}]*[^\W_]|[{_SIGNS}]+[^\W\d_][\w{_SIGNS}]*[^\W_]")
_SPACED = re.compile(rf"(?<![\w{_SIGNS}])(?:[\w@$!|+][ .\-_*]){{3,}}[\w@$!|+](?![\w{_SIGNS}])")
_RUN = re.compile(r"([^\W\d_])\1\1")
_LETTERS = re.compile(r"[^\W\d_]+")
#: Costs of the channel: a sign for a letter, a letter dropped from a run, a sign dropped, a separator that stands for nothing or for a word border.
SIGN_COST, RUN_COST, DROP_COST, JOIN_COST, BORDER_COST = 0.5, 0.3, 3.0, 0.1, 2.0
#: Tokens of up to so many characters are remembered once restored. Words known to part spaced phrases: so many, of up to so many letters, found so often at least.
REMEMBERED, WORDS, LONGEST, LEAST_N = 64, 50_000, 24, 3
#: Cost of each word of a spaced phrase, most being one word, and of one that is not known, besides its letters.
WORD_COST, UNKNOWN_COST = 4.0, 6.0


class CharModel:
    """Trigram costs (negative logarithms) over 64 character classes, bounded whatever the corpus, and costs of words by their counts."""

    ALPHABET = "abcdefghijklmnopqrstuvwxyzàâäáãåçèéêëìíîïñòóôöõùúûüýÿßœæø"

    def __init__(self, counts: np.ndarray, words: dict[str, int] | None = None):
        total = sum((words or {}).values())
        self.words = {w: math.log(total / n) + WORD_COST for w, n in (words or {}).items()}
        c = counts.reshape(64, 64, 64).astype(np.float64)
        bi, uni, last = c.sum(2), c.sum((1, 2)), c.sum((0, 1))
        p1 = (uni + 1) / (uni.sum() + 64)
        p2 = (bi + 4 * p1[None, :]) / (bi.sum(1, keepdims=True) + 4)
        self.cost = -np.log((c + 4 * p2[None, :, :]) / (c.sum(2, keepdims=True) + 4))
        self.alone = -np.log((last + 1) / (last.sum() + 64))

    def spells(self, word: str) -> bool:
        """Whether letters are likelier as a word than as letters that have nothing to do with each other."""
        if word in self.words or len(word) < 2:
            return len(word) > 1
        x = y = 0
        gain = 0.0
        for z in map(self.code, word + " "):
            gain += self.alone[z] - self.cost[x, y, z]
            x, y = y, z
        return bool(gain > 0)

    @classmethod
    def code(cls, ch: str) -> int:
        """Class of a character: 0 for a word border, 63 for a letter outside the alphabet."""
        return 0 if ch == " " else cls.ALPHABET.find(ch) + 1 or 63


_CODES = np.full(0x2000, 0, np.uint8)
for _c in range(0x2000):
    if chr(_c).isalpha():
        _CODES[_c] = CharModel.code(chr(_c).lower()[0])


def trigram_counts(text: str) -> np.ndarray:
    """Codes of all trigrams of a text's words with their borders."""
    u = np.frombuffer(text.encode("utf-32-le"), np.uint32)
    x = _CODES[np.minimum(u, 0x1FFF)].astype(np.int32)
    x = np.concatenate([[0, 0], x, [0]])
    t = (x[:-2] << 12) | (x[1:-1] << 6) | x[2:]
    # a place counts if its last character is a letter, or a border that follows one
    return t[(x[2:] > 0) | (x[1:-1] > 0)]


def lattice(token: str, spaced: bool = False) -> list[list[tuple[str, float]]]:
    """What each run of a token may stand for, with the channel's cost. In a spaced token every other character is a separator,
    which may be a word border, and no sign is dropped."""
    if spaced:
        whole = [[[o for o in opts if o[0]] or opts for opts in lattice(ch)] for ch in token[::2]]
        return [opts for units in whole for opts in (*units, [("", JOIN_COST), (" ", BORDER_COST)])][:-1]
    out, i, token = [], 0, token.lower()
    while i < len(token):
        ch, j = token[i], i
        while j < len(token) and token[j] == ch:
            j += 1
        n, i = j - i, j
        if ch.isalpha():
            opts = [(ch * n, 0.0)] if n <= 2 else [(ch, RUN_COST), (ch * 2, RUN_COST + 1.0)]
        elif ch in LEET:
            opts = [(c * min(n, 2), SIGN_COST * n) for c in LEET[ch]] + ([(c, SIGN_COST * n) for c in LEET[ch]] if n == 2 else [])
            opts.append(("", DROP_COST))
        else:
            opts = [("", JOIN_COST)]
        out.append(opts)
    return out


def restore(token: str, lm: CharModel, spaced: bool = False) -> str:
    """The word of least cost on the token's lattice, of a spaced token the words; letters that spell nothing the model supports stay alone. States
    are pairs of classes and paths share their beginnings, so time and memory are linear in the token."""
    best: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
    for opts in lattice(token, spaced):
        nxt: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        for (a, b), (cost, path) in best.items():
            for s, c in opts:
                x, y, total = a, b, cost + c
                for ch in s:
                    z = CharModel.code(ch)
                    total += lm.cost[x, y, z]
                    x, y = y, z
                if (x, y) not in nxt or total < nxt[x, y][0]:
                    nxt[x, y] = (total, (path, s) if s else path)
        best = nxt
    path = min((cost + lm.cost[a, b, 0], (a, b), path) for (a, b), (cost, path) in best.items())[2]
    parts = []
    while path:
        path, s = path
        parts.append(s)
    out = "".join(reversed(parts))
    if spaced:
        words = parted(out.replace(" ", ""), lm) if lm.words else out.split(" ")
        spelt = [lm.spells(w) for w in words]
        out = " ".join(w if known else " ".join(w) for w, known in zip(words, spelt)) if any(spelt) else token
    return out


def parted(letters: str, lm: CharModel) -> list[str]:
    """Words of least cost that make up the letters: known ones by their counts, others, of any length, by the trigram model."""
    whole, back = [0.0], [0]  # cost and start of the last word, of the letters up to a place
    inner, since, x, y = math.inf, 0, 0, 0  # the same for a word not known that ends here
    for i, ch in enumerate(letters):
        z = CharModel.code(ch)
        fresh = whole[i] + UNKNOWN_COST + lm.cost[0, 0, z]
        inner += lm.cost[x, y, z]
        x, y = y, z
        if fresh < inner:
            inner, since, x = fresh, i, 0
        best = (inner + lm.cost[x, y, 0], since)
        for j in range(max(0, i + 1 - LONGEST), i + 1):
            w = lm.words.get(letters[j : i + 1])
            if w is not None and whole[j] + w < best[0]:
                best = (whole[j] + w, j)
        whole.append(best[0])
        back.append(best[1])
    out, i = [], len(letters)
    while i:
        out.append(letters[back[i] : i])
        i = back[i]
    return out[::-1]


#: Kinds of characters: word characters that are no signs, signs, letters, what a spaced word is made of, what stands between. Code points from
#: 0x3000 on, among which are no signs, share the last place and count as letters.
_W, _S, _L, _A, _P = 1, 2, 4, 8, 16
_KIND = np.zeros(0x3001, np.uint8)
for _kind, _re in ((_W, rf"[^\W{_SIGNS}]"), (_S, f"[{_SIGNS}]"), (_L, r"[^\W\d_]"), (_A, r"[\w@$!|+]"), (_P, r"[ .\-_*]")):
    _KIND[[ord(c) for c in re.findall(_re, "".join(map(chr, range(0x3000))))]] |= _kind
_KIND[0x3000] = _W | _L | _A


def suspects(text: str) -> tuple[bool, bool, bool]:
    """Whether a text may hold words spelled with signs, spaced words, and words with letters repeated: conditions that every match of _WORD, _SPACED
    and _RUN fulfils, read from its characters."""
    x = np.frombuffer(text.encode(), np.uint8) if text.isascii() else np.frombuffer(text.encode("utf-32-le"), np.uint32)
    k = _KIND[np.minimum(x, 0x3000)] if x.itemsize > 1 else _KIND[x]
    if len(k) < 3:
        return False, False, False
    word, sign, letter = k & (_W | _S) > 0, k & _S > 0, k & _L > 0
    signs = bool((((k[:-2] & _W > 0) & sign[1:-1] | sign[:-2] & letter[1:-1]) & word[2:]).any())
    step = (k[:-1] & _A > 0) & (k[1:] & _P > 0)
    spaced = len(k) > 6 and bool((step[:-5] & step[2:-3] & step[4:-1] & (k[6:] & _A > 0)).any())
    same = x[1:] == x[:-1]
    runs = bool((same[:-1] & same[1:] & letter[2:]).any())
    return signs, spaced, runs


def restored(text: str, lm: CharModel, known: dict[str, str]) -> str:
    """The text with its disguised words restored; a text without any comes back as it is."""
    signs, spaced, runs = suspects(text)

    def put(m: re.Match, spaced: bool = False) -> str:
        token = m.group()
        if len(token) > REMEMBERED:
            return restore(token, lm, spaced)
        key = " " + token if spaced else token
        if key not in known:
            if len(known) > 50_000:
                known.clear()
            known[key] = restore(token, lm, spaced)
        return known[key]

    if spaced:
        text = _SPACED.sub(lambda m: put(m, True), text)
        signs, _, runs = suspects(text)
    if signs:
        text = _WORD.sub(put, text)
        runs = suspects(text)[2]
    if runs and _RUN.search(text):
        text = _LETTERS.sub(lambda m: put(m) if _RUN.search(m.group()) else m.group(), text)
    return text


def word_features(w: str) -> list[int]:
    """64-bit features of a word: the word itself and its beginnings."""
    b = w.encode()
    return [xxhash.xxh3_64_intdigest(b, 1), *(xxhash.xxh3_64_intdigest(b[:n], 2) for n in PREFIXES if n < len(b))]


def features(text: str) -> np.ndarray:
    """Distinct features of a text."""
    got: list[int] = []
    for w in set(_LETTERS.findall(text.lower())):
        got += word_features(w)
    return np.unique(np.array(got, np.uint64))


def char_model(docs: DataFrame, text_col: str = "text") -> CharModel:
    """Counts of trigrams and words over all documents; 64 ** 3 and WORDS counts at most reach the driver."""
    prepare(docs.sparkSession)

    def run(batches):
        total, words = np.zeros(1 << 18, np.int64), Counter()

        def counted():
            return pa.RecordBatch.from_pydict({"g": pa.array([-1] * len(words), pa.int32()), "w": pa.array(list(words), pa.string()), "n": pa.array(list(words.values()), pa.int64())})

        for b in batches:
            held, size = [], 0
            for t in [*(x or "" for x in b.column(0).to_pylist()), None]:
                if t:
                    held.append(t)
                    size += len(t)
                if held and (t is None or size > 1 << 19):
                    text = "\n".join(held)
                    total += np.bincount(trigram_counts(text), minlength=1 << 18)
                    words.update(w for w in _LETTERS.findall(text.lower()) if len(w) <= LONGEST)
                    held, size = [], 0
            if len(words) > 200_000:
                yield counted()
                words.clear()
        at = np.flatnonzero(total)
        yield counted()
        yield pa.RecordBatch.from_pydict({"g": pa.array(at, pa.int32()), "w": pa.array([""] * len(at), pa.string()), "n": pa.array(total[at], pa.int64())})

    both = docs.select(docs[text_col].cast("string").alias("text")).mapInArrow(lean(run), "g int, w string, n long").groupBy("g", "w").agg(F.sum("n").alias("n"))
    rows = both.where((F.col("g") >= 0) | (F.col("n") >= LEAST_N)).orderBy(F.col("g") < 0, F.desc("n"), "w").limit((1 << 18) + WORDS).toArrow()
    g, n = np.asarray(rows.column("g")), np.asarray(rows.column("n"))
    counts = np.zeros(1 << 18, np.int64)
    counts[g[g >= 0]] = n[g >= 0]
    at = np.flatnonzero(g < 0)[:WORDS]
    return CharModel(counts, dict(zip(rows.column("w").take(pa.array(at)).to_pylist(), n[at].tolist())))


class Scorer:
    """Weights by feature hash and an intercept."""

    def __init__(self, keys: np.ndarray, weights: np.ndarray, bias: float):
        self.keys, self.weights, self.bias = keys, weights, bias

    def reader(self):
        """text -> score, with what is known of words remembered up to a bound."""
        at = {int(k): i for i, k in enumerate(self.keys.tolist())}
        weights = self.weights.tolist()

        class Known(dict):
            def __missing__(known, w):
                if len(known) > 100_000:
                    known.clear()
                known[w] = got = tuple(at[f] for f in word_features(w) if f in at)
                return got

        known = Known()

        def score(text: str) -> float:
            hits: set[int] = set()
            for f in map(known.__getitem__, set(_LETTERS.findall(text.lower()))):
                if f:
                    hits.update(f)
            z = self.bias + sum(weights[i] for i in sorted(hits))
            return 1.0 / (1.0 + math.exp(-max(-30.0, min(30.0, z))))

        return score


def _g(n1, n0, t1, t0):
    """Signed G statistic of a feature found in n1 of t1 toxic and n0 of t0 other documents."""
    total, n = t1 + t0, n1 + n0

    def term(o, e):
        return np.where(o > 0, o * np.log(np.maximum(o, 1e-9) / np.maximum(e, 1e-9)), 0.0)

    g = 2 * (term(n1, n * t1 / total) + term(n0, n * t0 / total) + term(t1 - n1, (total - n) * t1 / total) + term(t0 - n0, (total - n) * t0 / total))
    return np.where(n1 * t0 > n0 * t1, g, -g)


def train(rows: list[tuple[np.ndarray, int]], size: int, steps: int = 1200, rate: float = 0.5, decay: float = 1e-3) -> tuple[np.ndarray, float]:
    """Logistic regression over rows of active feature numbers, by full-batch gradient descent with momentum. The rarer class weighs more, by
    the root of the odds, so that one strong word is enough in a long text."""
    y = np.array([r[1] for r in rows], np.float64)
    owner = np.repeat(np.arange(len(rows)), [len(r[0]) for r in rows])
    active = np.concatenate([r[0] for r in rows]).astype(np.int64) if len(owner) else np.zeros(0, np.int64)
    share = min(max(y.mean(), 1e-3), 1 - 1e-3)
    weight = np.where(y > 0, ((1 - share) / share) ** 0.5, 1.0)
    w, b, vw, vb = np.zeros(size), 0.0, np.zeros(size), 0.0
    for _ in range(steps):
        z = b + np.bincount(owner, w[active], minlength=len(rows))
        e = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y) * weight / len(rows)
        gw = np.bincount(active, e[owner], minlength=size) + decay * w / max(1, len(rows)) ** 0.5
        vw, vb = 0.9 * vw + gw, 0.9 * vb + e.sum()
        w, b = w - rate * 4 * vw, b - rate * vb
    return w, b


def fit(docs: DataFrame, labels: DataFrame, lm: CharModel, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Scorer:
    """A scorer from at most SAMPLE labelled rows, drawn by hash; what reaches the driver is bounded by SAMPLE and FEATURES."""
    spark = docs.sparkSession
    prepare(spark)
    y = labels.where(labels[label_col].isNotNull() & labels[id_col].isNotNull()).groupBy(labels[id_col].cast("long").alias("id")).agg(F.max(labels[label_col]).cast("int").alias("y"))
    chosen = y.orderBy(F.xxhash64("id"), "id").limit(SAMPLE)
    rows = docs.select(docs[id_col].cast("long").alias("id"), docs[text_col].cast("string").alias("text")).where("text is not null").join(F.broadcast(chosen), "id").select("id", "text", "y")

    def found(batches):
        known: dict[str, str] = {}
        for b in batches:
            got = [features(restored(t, lm, known)).tobytes() for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_pydict({"id": b.column(0), "y": b.column(2), "f": pa.array(got, pa.binary())})

    sample = common.materialise(rows.mapInArrow(lean(found), "id long, y int, f binary"), "toxic-sample")
    totals = {r.y: r.n for r in sample.groupBy("y").agg(F.count("*").alias("n")).collect()}
    t1, t0 = totals.get(1, 0), totals.get(0, 0)
    if not t1 or not t0:
        common.discard(sample)
        return Scorer(np.zeros(0, np.uint64), np.zeros(0), 30.0 if t1 else -30.0)

    def counted(batches):
        seen = {0: [], 1: []}
        for b in batches:
            for k, f in zip(b.column(0).to_pylist(), b.column(1)):
                seen[k].append(np.frombuffer(f.as_buffer(), np.uint64))
        for k, parts in seen.items():
            if parts:
                f, n = np.unique(np.concatenate(parts), return_counts=True)
                yield pa.RecordBatch.from_pydict({"f": pa.array(f.view(np.int64)), "n1": pa.array(n * k, pa.int64()), "n0": pa.array(n * (1 - k), pa.int64())})

    by = sample.select("y", "f").mapInArrow(lean(counted), "f long, n1 long, n0 long").groupBy("f").agg(F.sum("n1").alias("n1"), F.sum("n0").alias("n0"))
    # only what leans to the toxic side can pass LEAST_G with n1 of 2 or more; the strongest by share are taken for the exact statistic
    top = by.where(F.col("n1") >= 2).where(F.col("n1") * t0 > F.col("n0") * t1).orderBy(F.desc(F.col("n1") * F.log(F.col("n1") * t0 / ((F.col("n0") + 0.5) * t1))), "f").limit(FEATURES).toArrow()
    f, n1, n0 = (np.asarray(top.column(c)) for c in ("f", "n1", "n0"))
    keep = _g(n1.astype(float), n0.astype(float), float(t1), float(t0)) >= LEAST_G
    keys = np.sort(f[keep].astype(np.int64).view(np.uint64))

    def active(batches):
        for b in batches:
            got = []
            for x in b.column(1):
                g = np.frombuffer(x.as_buffer(), np.uint64)
                at = np.minimum(np.searchsorted(keys, g), max(0, len(keys) - 1))
                got.append((at[keys[at] == g] if len(keys) and len(g) else np.zeros(0)).astype(np.int32).tobytes())
            yield pa.RecordBatch.from_pydict({"id": b.column(2), "y": b.column(0), "at": pa.array(got, pa.binary())})

    t = sample.select("y", "f", "id").mapInArrow(lean(active), "id long, y int, at binary").toArrow().sort_by([("id", "ascending"), ("at", "ascending")])
    common.discard(sample)
    w, b = train([(np.frombuffer(x, np.int32), k) for x, k in zip(t.column("at").to_pylist(), t.column("y").to_pylist())], len(keys))
    return Scorer(keys, w, b)


def scored(docs: DataFrame, lm: CharModel, model: Scorer, held_out, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row, on its whole text."""
    prepare(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast((lm, model))

    def run(batches):
        lm, score = shared.value[0], shared.value[1].reader()
        known: dict[str, str] = {}
        for b in batches:
            s = [score(restored(t, lm, known) if t else "") for t in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_pydict({"doc_id": b.column(0), "held_out": b.column(1), "score": pa.array(s, pa.float64()), "predicted": pa.array([int(x >= 0.5) for x in s], pa.int32())})

    return docs.select(docs[id_col].cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), docs[text_col].cast("string").alias("text")).mapInArrow(lean(run), OUT)


def models(docs: DataFrame, labels: DataFrame) -> tuple[CharModel, Scorer]:
    """Both models for a corpus: counts from all documents, labels only from rows of which crc32(doc_id) mod 5 is not 0."""
    lm = char_model(docs)
    return lm, fit(docs, labels.where(fold(labels["doc_id"], 5) != 0), lm)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    lm, model = models(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return scored(docs, lm, model, fold(docs["doc_id"], 5) == 0)


def without_toxic(docs: DataFrame, lm: CharModel, model: Scorer, text_col: str = "text") -> DataFrame:
    """``docs`` without rows predicted toxic: scored and filtered in one map-only pass that keeps all columns."""
    prepare(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast((lm, model))
    at = docs.columns.index(text_col)

    def run(batches):
        lm, score = shared.value[0], shared.value[1].reader()
        known: dict[str, str] = {}
        for b in batches:
            keep = [score(restored(t, lm, known) if t else "") < 0.5 for t in b.column(at).to_pylist()]
            yield b.filter(pa.array(keep, pa.bool_()))

    return docs.mapInArrow(lean(run), docs.schema)
