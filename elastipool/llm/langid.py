"""Language identification: averaged hashed subword embeddings under a linear softmax.

Subwords are the byte 2-, 3- and 4-grams of the text with A-Z in lower case, hashed into ``BUCKETS`` rows of an embedding; a text is
the mean of its subwords' embeddings, and a linear softmax over it gives the languages. Embedding and softmax are trained together by
stochastic gradient descent in numpy, on at most ``PER_LANG`` rows of each of the ``LANGS`` most frequent languages, chosen by hash. A fifth of these is kept from
training: on it a temperature calibrates the scores, and the score that all but ``REJECT`` of its right answers reach becomes the threshold below
which ``rejected`` is true. Prediction reads whole texts in bounded pieces, map-only.

Text that is null or has no letter: ``und``, score 0, rejected. With nothing to learn from every row is ``und``. Null doc_id: predicted, held_out
false. Repeated rows are predicted alike; other columns are never inputs; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from elastipool.llm import common
from elastipool.llm.common import lean, prepare, table

BUCKETS, DIM, GRAMS, PER_LANG, LANGS, EPOCHS, BATCH, RATE, REJECT = 1 << 15, 16, (2, 3, 4), 600, 256, 6, 16, 0.5, 0.01
PIECE = 1 << 20
UND = "und"
OUT = "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean"
_MULT = {2: np.uint32(0x9E3779B1), 3: np.uint32(0x85EBCA77), 4: np.uint32(0xC2B2AE3D)}


def gram_ids(x: np.ndarray, n: int) -> np.ndarray:
    """Bucket of the n-gram at each place of a byte array."""
    v = x[: len(x) - n + 1].astype(np.uint32)
    for i in range(1, n):
        v = (v << np.uint32(8)) | x[i : len(x) - n + 1 + i]
    h = v * _MULT[n]
    h ^= h >> np.uint32(15)
    h = h * np.uint32(0x2C1B3C6D)
    return (h >> np.uint32(17)).astype(np.int32)


def lower(x: np.ndarray) -> np.ndarray:
    return np.where((x >= 65) & (x <= 90), x + 32, x).astype(np.uint8)


def counts(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(bucket, share) of a text's subwords."""
    x = lower(np.frombuffer(text, np.uint8))
    total = np.zeros(BUCKETS, np.int64)
    for a in range(0, len(x), PIECE):
        for n in GRAMS:
            part = x[a : a + PIECE + n - 1]
            if len(part) >= n:
                total += np.bincount(gram_ids(part, n), minlength=BUCKETS)
    at = np.flatnonzero(total)
    return at.astype(np.int32), (total[at] / max(1, total.sum())).astype(np.float32)


class Model:
    """logits = mean(embedding) @ weights + bias, divided by the temperature; tables are bounded by BUCKETS and the languages."""

    def __init__(self, langs: list[str], rows: list[tuple[np.ndarray, np.ndarray, int]], seed: int = 7):
        self.langs, rng = langs, np.random.default_rng(seed)
        self.emb = rng.normal(0, 0.1, (BUCKETS, DIM)).astype(np.float32)
        self.w, self.b = np.zeros((DIM, len(langs)), np.float32), np.zeros(len(langs), np.float32)
        self.w += rng.normal(0, 0.1, self.w.shape)
        self.t, self.threshold = 1.0, 0.0
        order = rng.permutation(len(rows))
        kept, train = order[: len(rows) // 5], order[len(rows) // 5 :]
        for epoch in range(EPOCHS):
            rate = RATE * (1 - epoch / EPOCHS)
            for k in range(0, len(train), BATCH):
                part = train[k : k + BATCH]
                z = np.stack([rows[i][1] @ self.emb[rows[i][0]] for i in part])
                p = self._softmax(z @ self.w + self.b)
                p[np.arange(len(part)), [rows[i][2] for i in part]] -= 1
                p /= len(part)
                back = p @ self.w.T
                self.w -= rate * 10 * z.T @ p
                self.b -= rate * p.sum(0)
                for j, i in enumerate(part):
                    # the mean spreads a gradient thinly over many rows; their step is scaled up by the usual number of them
                    self.emb[rows[i][0]] -= rate * 200 * rows[i][1][:, None] * back[j]
            train = rng.permutation(train)
        if len(kept):
            logits = np.stack([rows[i][1] @ self.emb[rows[i][0]] for i in kept]) @ self.w + self.b
            y = np.array([rows[i][2] for i in kept])
            loss = {t: -np.log(self._softmax(logits / t)[np.arange(len(y)), y] + 1e-9).mean() for t in (0.25, 0.35, 0.5, 0.7, 1.0, 1.4, 2.0, 2.8, 4.0)}
            self.t = min(loss, key=loss.get)
            p = self._softmax(logits / self.t)
            right = p.max(1)[p.argmax(1) == y]
            self.threshold = float(np.quantile(right, REJECT)) if len(right) else 0.0
        self.table = (self.emb @ self.w).astype(np.float32)

    @staticmethod
    def _softmax(x: np.ndarray) -> np.ndarray:
        e = np.exp(x - x.max(-1, keepdims=True))
        return e / e.sum(-1, keepdims=True)

    def scores(self, texts: list[bytes]) -> np.ndarray:
        """Softmax of each text; pieces of texts are scored together."""
        out = np.zeros((len(texts), len(self.langs)))
        grams = np.zeros(len(texts))
        held, size = [], 0

        def flush():
            x = lower(np.frombuffer(b"".join(p for _, p in held), np.uint8))
            ends = np.cumsum([len(p) for _, p in held])
            at = np.array([i for i, _ in held])
            for n in GRAMS:
                ok = np.diff(ends, prepend=0) >= n
                if not ok.any():
                    continue
                cuts = np.stack([(ends - np.diff(ends, prepend=0))[ok], (ends - n + 1)[ok]], 1).ravel()
                got = self.table[gram_ids(x, n)]
                got = np.concatenate([got, np.zeros((n, got.shape[1]), np.float32)])
                np.add.at(out, at[ok], np.add.reduceat(got, cuts, axis=0, dtype=np.float64)[::2])
                np.add.at(grams, at[ok], cuts[1::2] - cuts[::2])

        for i, t in enumerate(texts):
            for a in range(0, len(t), PIECE):
                held.append((i, t[a : a + PIECE]))
                size += len(held[-1][1])
                if size >= PIECE:
                    flush()
                    held, size = [], 0
        if held:
            flush()
        return self._softmax((out / np.maximum(grams, 1)[:, None] + self.b) / self.t)


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model | None:
    """A model of the languages of ``docs``; at most PER_LANG rows a language and LANGS languages reach the driver, as subword counts. Counts of the
    languages come first, so that rows that cannot be among the chosen ones are left out where they lie and no language makes a large group."""
    prepare(docs.sparkSession)
    rows = docs.where(docs[lang_col].isNotNull() & docs[text_col].isNotNull() & docs[id_col].isNotNull())
    keyed = rows.select(rows[id_col].alias("id"), rows[lang_col].alias("lang")).withColumn("h", F.xxhash64("id").bitwiseAND(F.lit((1 << 32) - 1)))
    sizes = {r.lang: r.n for r in keyed.groupBy("lang").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "lang").limit(LANGS).collect()}
    if not sizes:
        return None
    # of n rows with even hashes the PER_LANG least lie below this, but for a chance of one in millions; then the sample is a little smaller
    most = docs.sparkSession.createDataFrame([(y, int(min(1.0, (2 * PER_LANG + 200) / n) * (1 << 32))) for y, n in sizes.items()], "lang string, most long")
    rank = F.row_number().over(Window.partitionBy("lang").orderBy("h", "id"))
    chosen = keyed.join(F.broadcast(most), "lang").where("h <= most").withColumn("r", rank).where(F.col("r") <= PER_LANG).select("id")
    sample = rows.select(rows[id_col].alias("id"), rows[text_col].alias("text"), rows[lang_col].alias("lang")).join(F.broadcast(chosen.distinct()), "id", "left_semi")

    def run(batches):
        for b in batches:
            got = [counts(t or b"") for t in common.pairs_of(b, "text")]
            yield pa.RecordBatch.from_pydict({"id": b.column(0), "at": pa.array([g[0].tobytes() for g in got], pa.binary()), "share": pa.array([g[1].tobytes() for g in got], pa.binary()), "lang": b.column(2)})

    t = sample.select(F.col("id").cast("string").alias("id"), "text", "lang").mapInArrow(lean(run), "id string, at binary, share binary, lang string").toArrow().sort_by([("id", "ascending"), ("lang", "ascending"), ("at", "ascending")])
    langs = sorted(set(t.column("lang").to_pylist()))
    if not langs:
        return None
    return Model(langs, [(np.frombuffer(a, np.int32), np.frombuffer(s, np.float32), langs.index(y)) for a, s, y in zip(t.column("at").to_pylist(), t.column("share").to_pylist(), t.column("lang").to_pylist()) if a])


def identified(docs: DataFrame, model: Model | None, held_out, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Language, calibrated score and rejection of every row."""
    prepare(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model and (model.langs, model.table, model.b, model.t, model.threshold))

    def run(batches):
        m = None
        if shared.value:
            m = Model.__new__(Model)
            m.langs, m.table, m.b, m.t, m.threshold = shared.value
        for b in batches:
            texts = b.column(2).to_pylist()
            real = [i for i, t in enumerate(texts) if m and t and any(map(str.isalpha, t))]
            pred, score, no = [UND] * len(texts), [0.0] * len(texts), [True] * len(texts)
            if real:
                p = m.scores([texts[i].encode() for i in real])
                for i, k, s in zip(real, p.argmax(1).tolist(), p.max(1).tolist()):
                    pred[i], score[i], no[i] = m.langs[k], min(1.0, s), s < m.threshold
            yield pa.RecordBatch.from_pydict({"doc_id": b.column(0), "held_out": b.column(1), "lang_pred": pa.array(pred, pa.string()), "score": pa.array(score, pa.float64()), "rejected": pa.array(no, pa.bool_())})

    return docs.select(docs[id_col].cast("long").alias("doc_id"), F.coalesce(held_out, F.lit(False)).alias("held_out"), docs[text_col].cast("string").alias("text")).mapInArrow(lean(run), OUT)


def fold(col, n: int):
    return F.crc32(col.cast("string").cast("binary")) % n


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang")
    out = fold(docs["doc_id"], 4) == 2
    return identified(docs, fit(docs.where(~out)), out)
