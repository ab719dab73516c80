"""Quality classifier by co-training of two views.

The content view sees the text alone: byte trigrams and layout (lines, letter case, marks,
digits, how far it compresses).  The metadata view sees the page's declared fields alone
(source, language, length and their pairs).  Trigrams, layout and metadata are log-odds
models; a view's calibration on held-out labels turns its log-odds into a probability.  In each round either view
labels the documents it is sure of for the other; at the end a logistic model of both
calibrated views scores all documents.

Only labels are sampled: at most ``max_labelled`` labelled rows, taken in hash order, each
reduced to at most 2**14 counts.  Every other document is in the pool: each round scores all of
them on the executors and adds up there what the sure ones hold, so the driver gets vectors of fixed size.
"""

from __future__ import annotations

import dataclasses
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import give_back, lean

DIMS, SLOTS = 1 << 14, 1 << 12
FIELDS = ["source", "lang", "n_chars"]
#: Shares of a document's trigrams are added as whole multiples of 1 / SCALE, so the order of adding does not matter.
SCALE = 1 << 30

#: Byte classes: 0 other letters and bytes, 1 upper case, 2 digits, 3 blanks, 4 sentence marks, 5 other marks.
CLASSES = np.zeros(256, np.uint8)
CLASSES[65:91] = 1
CLASSES[48:58] = 2
CLASSES[[9, 10, 11, 12, 13, 32]] = 3
CLASSES[[33, 34, 35, 36, 37, 38, 40, 41, 42, 43, 47, 58, 59, 60, 61, 62, 64, 91, 92, 93, 94, 95, 96, 123, 124, 125, 126]] = 5
CLASSES[[39, 44, 45, 46, 63]] = 4


def trigrams(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """All texts' bytes, each text's bounds, and the hashed trigram that begins at each byte."""
    raw = [(t + "\n\n").encode("utf-8", "surrogatepass") for t in texts]
    bounds = np.r_[0, np.cumsum([len(r) for r in raw])]
    flat = np.frombuffer(b"".join(raw), np.uint8)
    x = flat.astype(np.uint32)
    h = x[:-2] * np.uint32(0x9E3779B1) + x[1:-1] * np.uint32(0x85EBCA77) + x[2:] * np.uint32(0xC2B2AE3D)
    return flat, bounds, ((h ^ (h >> np.uint32(15))) >> np.uint32(4)) & np.uint32(DIMS - 1)


def layout(flat: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Per text: bytes, line feeds, size after compression, and shares of the byte classes."""
    kinds = CLASSES[flat]
    sizes = np.diff(bounds) - 2
    cols = [sizes, np.add.reduceat((flat == 10).astype(np.int32), bounds[:-1]) - 2]
    cols += [np.add.reduceat((kinds == k).astype(np.int32), bounds[:-1]) / np.maximum(sizes, 1) for k in (1, 2, 4, 5)]
    raw = memoryview(flat)
    squeezed = [len(zlib.compress(raw[a : max(a, b - 2)], 1)) for a, b in zip(bounds.tolist(), bounds[1:].tolist())]
    return np.stack([*cols[:2], np.array(squeezed), *cols[2:]], axis=1)


def slot(name: str, value) -> int:
    return zlib.crc32(f"{name}={value}".encode("utf-8", "surrogatepass")) % SLOTS


def layout_features(shapes: np.ndarray) -> np.ndarray:
    """Hashed indices of a text's layout, one column a measure."""
    out = []
    for size, feeds, squeezed, *shares in shapes.tolist():
        row = [slot("lines", int(np.log2(feeds + 1))), slot("width", int(np.log2(size / (feeds + 1) + 1)))]
        row.append(slot("squeezed", (int(np.log2(size + 1)), int(12 * squeezed / (size + 12)))))
        out.append(row + [slot(f"share{k}", int(np.sqrt(s) * 16)) for k, s in enumerate(shares)])
    return np.array(out, np.int32).reshape(len(shapes), -1)


def meta_features(fields: list[tuple]) -> np.ndarray:
    """Hashed indices of a document's declared fields and their pairs, one column each; null is a value like any other."""
    out = []
    for source, lang, n_chars in fields:
        length = None if n_chars is None else int(2 * np.log2(abs(n_chars) + 1))
        pairs = {"source": source, "lang": lang, "length": length, "source-lang": (source, lang), "source-length": (source, length), "lang-length": (lang, length)}
        out.append([slot(k, v) for k, v in pairs.items()])
    return np.array(out, np.int32).reshape(len(fields), -1)


def rows_of(batch: pa.RecordBatch) -> tuple[list[str], list[tuple]]:
    texts = [t or "" for t in batch.column("text").to_pylist()]
    return texts, list(zip(*(batch.column(f).to_pylist() for f in FIELDS)))


@dataclasses.dataclass
class Sample:
    ids: np.ndarray
    layout: np.ndarray
    meta: np.ndarray
    bounds: np.ndarray
    index: np.ndarray
    share: np.ndarray

    def scores(self, w: Weights) -> tuple[np.ndarray, np.ndarray]:
        """Log-odds of the content view (trigrams, layout) and of the metadata view."""
        grams = np.add.reduceat(w.grams[self.index] * self.share, self.bounds[:-1]) if len(self.ids) else np.empty(0)
        return np.c_[grams, w.layout[self.layout].sum(axis=1)], w.meta[self.meta].sum(axis=1)[:, None]

    def counts(self, for_content: np.ndarray, for_meta: np.ndarray) -> Counts:
        """Of the rows with a class (-1: none), for either view."""
        out = Counts.zero()
        for k in (0, 1):
            rows = (for_content == k).astype(float)
            out.grams[k] = np.bincount(self.index, self.share * np.repeat(rows, np.diff(self.bounds)), DIMS)
            out.layout[k] = np.bincount(self.layout.ravel(), np.repeat(rows, self.layout.shape[1]), SLOTS)
            out.n_content[k] = rows.sum()
            rows = (for_meta == k).astype(float)
            out.meta[k] = np.bincount(self.meta.ravel(), np.repeat(rows, self.meta.shape[1]), SLOTS)
            out.n_meta[k] = rows.sum()
        return out


@dataclasses.dataclass
class Counts:
    """Per class (bad, good): summed trigram shares, counts of layout and of metadata slots, and documents behind either view."""

    grams: np.ndarray
    layout: np.ndarray
    meta: np.ndarray
    n_content: np.ndarray
    n_meta: np.ndarray

    @staticmethod
    def zero() -> Counts:
        return Counts(np.zeros((2, DIMS)), np.zeros((2, SLOTS)), np.zeros((2, SLOTS)), np.zeros(2), np.zeros(2))

    def flat(self) -> np.ndarray:
        return np.r_[np.rint(self.grams.ravel() * SCALE), self.layout.ravel(), self.meta.ravel(), self.n_content, self.n_meta].astype(np.int64)

    @staticmethod
    def of(flat: np.ndarray) -> Counts:
        grams, layout, meta, n_content, n_meta = np.split(flat.astype(float), np.cumsum([2 * DIMS, 2 * SLOTS, 2 * SLOTS, 2]))
        return Counts(grams.reshape(2, -1) / SCALE, layout.reshape(2, -1), meta.reshape(2, -1), n_content, n_meta)

    def __add__(self, other: Counts) -> Counts:
        return Counts(*(getattr(self, f.name) + getattr(other, f.name) for f in dataclasses.fields(self)))


@dataclasses.dataclass
class Weights:
    """Log-odds of each trigram, layout slot and metadata slot."""

    grams: np.ndarray
    layout: np.ndarray
    meta: np.ndarray

    @staticmethod
    def fit(c: Counts) -> Weights:
        bad, good = c.grams / np.maximum(c.n_content, 1e-9)[:, None]
        return Weights(np.log((good + 1e-5) / (bad + 1e-5)), slot_odds(c.layout, c.n_content), slot_odds(c.meta, c.n_meta))

    def scores(self, texts: list[str], fields: list[tuple]) -> tuple[np.ndarray, np.ndarray, Features]:
        """As Sample.scores, and what they were made from."""
        flat, bounds, h = trigrams(texts)
        f = Features(bounds, h, layout_features(layout(flat, bounds)), meta_features(fields))
        w = np.r_[self.grams[h], 0.0, 0.0]
        w[bounds[1:] - 1] = w[bounds[1:] - 2] = 0.0
        grams = np.add.reduceat(w, bounds[:-1]) / np.maximum(np.diff(bounds) - 2, 1)
        return np.c_[grams, self.layout[f.layout].sum(axis=1)], self.meta[f.meta].sum(axis=1)[:, None], f


@dataclasses.dataclass
class Features:
    bounds: np.ndarray
    h: np.ndarray
    layout: np.ndarray
    meta: np.ndarray


def slot_odds(counts: np.ndarray, n: np.ndarray) -> np.ndarray:
    bad, good = np.log(counts + (4 * n / n.sum())[:, None]) - np.log(np.maximum(n, 1e-9))[:, None]
    return good - bad


def sample_features(df: DataFrame, ids: DataFrame) -> Sample:
    """Sparse features of the documents in ``ids`` (bounded by the caller), on the driver."""

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                texts, fields = rows_of(part)
                flat, bounds, h = trigrams(texts)
                shapes, meta = layout_features(layout(flat, bounds)), meta_features(fields)
                index, share = [], []
                for a, b in zip(bounds.tolist(), bounds[1:].tolist()):
                    u, c = np.unique(h[a : max(b - 2, a + 1)], return_counts=True)
                    index.append(u.astype(np.int16))
                    share.append((c / max(b - 2 - a, 1)).astype(np.float32))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(list(shapes), pa.list_(pa.int32())), pa.array(list(meta), pa.list_(pa.int32())), pa.array(index, pa.list_(pa.int16())), pa.array(share, pa.list_(pa.float32()))], ["doc_id", "layout", "meta", "index", "share"])

    chosen = df.join(F.broadcast(ids), "doc_id", "left_semi").dropDuplicates(["doc_id"])
    got = chosen.mapInArrow(lean(run), "doc_id long, layout array<int>, meta array<int>, index array<short>, share array<float>").toArrow().combine_chunks()
    if not len(got):  # no labelled document is in the table
        none = np.empty((0, 1), np.int32)
        return Sample(np.empty(0, np.int64), none, none, np.zeros(1, np.int64), np.empty(0, np.int16), np.empty(0, np.float32))
    order = np.argsort(got["doc_id"].to_numpy())
    got = got.take(pa.array(order))
    index, share = got["index"].combine_chunks(), got["share"].combine_chunks()
    bounds = index.offsets.to_numpy().astype(np.int64)
    index, share = index.flatten().to_numpy(), share.flatten().to_numpy()
    shapes, meta = (got[c].combine_chunks().flatten().to_numpy().reshape(len(got), -1) for c in ("layout", "meta"))
    return Sample(got["doc_id"].to_numpy(), shapes, meta, bounds - bounds[0], index, share)


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, steps: int = 50) -> np.ndarray:
    """Weights and intercept (last) by damped Newton steps."""
    x1 = np.c_[x, np.ones(len(x))]
    w = np.zeros(x1.shape[1])
    penalty = np.diag(np.r_[np.full(x1.shape[1] - 1, ridge), 1e-3])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x1 @ w, -30, 30)))
        step = np.linalg.solve((x1 * (p * (1 - p) + 1e-6)[:, None]).T @ x1 + penalty, x1.T @ (y - p) - penalty @ w)
        w = w + np.clip(step, -5, 5)
        if np.abs(step).max() < 1e-6:
            break
    return w


def prob(w: np.ndarray, x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x @ w[:-1] + w[-1], -30, 30)))


def logit(p: np.ndarray) -> np.ndarray:
    return np.log(np.clip(p, 1e-6, 1) / np.clip(1 - p, 1e-6, 1))


@dataclasses.dataclass
class Model:
    """Weights of both views, their calibrations and combination; ``cut`` is the lowest kept probability, ``rounds`` the
    numbers of documents labelled in each round for the metadata view and for the content view."""

    weights: Weights
    content_cal: np.ndarray
    meta_cal: np.ndarray
    joint: np.ndarray
    cut: float
    rounds: list[tuple[int, int]]

    def probabilities(self, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        pa_, pb = prob(self.content_cal, a), prob(self.meta_cal, b)
        return pa_, pb, prob(self.joint, np.c_[logit(pa_), logit(pb)])

    def score(self, texts: list[str], fields: list[tuple]) -> list[np.ndarray]:
        a, b, _ = self.weights.scores(texts, fields)
        return [np.round(x, 6) for x in self.probabilities(a, b)]

    def keeps(self, p: np.ndarray) -> np.ndarray:
        return p >= np.round(self.cut, 6)


def classes_of(p: np.ndarray, sure: float) -> np.ndarray:
    return np.where(p > sure, 1, np.where(p < 1 - sure, 0, -1))


def pool_counts(docs: DataFrame, known: np.ndarray, weights: Weights, content_cal: np.ndarray, meta_cal: np.ndarray, sure: float) -> Counts:
    """What all documents but ``known`` (sorted ids) hold that one view is sure of, counted for the other view."""

    def run(batches: Iterator[pa.RecordBatch]):
        total = Counts.zero()
        for batch in batches:
            for i in range(0, batch.num_rows, 512):
                part = batch.slice(i, 512)
                free = [d is None or known[min(np.searchsorted(known, d), len(known) - 1)] != d for d in part.column("doc_id").to_pylist()]
                part = part.filter(pa.array(free, pa.bool_()))
                if not part.num_rows:
                    continue
                a, b, f = weights.scores(*rows_of(part))
                for_meta, for_content = classes_of(prob(content_cal, a), sure), classes_of(prob(meta_cal, b), sure)
                sizes = np.diff(f.bounds)
                each = np.repeat(1 / np.maximum(sizes - 2, 1), sizes)
                each[f.bounds[1:] - 1] = each[f.bounds[1:] - 2] = 0.0
                for k in (0, 1):
                    if (rows := for_content == k).any():
                        total.grams[k] += np.bincount(f.h, (each * np.repeat(rows, sizes))[:-2], DIMS)
                        total.layout[k] += np.bincount(f.layout[rows].ravel(), minlength=SLOTS)
                        total.n_content[k] += rows.sum()
                    total.meta[k] += np.bincount(f.meta[for_meta == k].ravel(), minlength=SLOTS)
                    total.n_meta[k] += (for_meta == k).sum()
        flat = total.flat()
        at = np.flatnonzero(flat)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(flat[at])], ["slot", "n"])

    got = docs.mapInArrow(lean(run), "slot int, n long").groupBy("slot").agg(F.sum("n").alias("n")).toArrow()
    flat = Counts.zero().flat()
    flat[got["slot"].to_numpy()] = got["n"].to_numpy()
    return Counts.of(flat)


def cotrain(s: Sample, labels: dict[int, int], pool: DataFrame, rounds: int = 3, sure: float = 0.97, lost_good: float = 0.002, always_below: float = 0.05) -> Model | None:
    """Fits on labelled rows and confident pseudo-labels of ``pool``; None unless both classes have labels.

    A third of the labelled rows is held out for calibration and for ``cut``: the ``lost_good`` quantile of the
    held-out good documents, but 0.5 at most and ``always_below`` at least, so that however few
    are held out, and however odd or mislabelled some are, the surely bad stay rejected.  Rounds end early once they change nothing.
    """
    y = np.array([labels.get(int(i), -1) for i in s.ids])
    known = np.flatnonzero(y >= 0)
    if len(known) < 10 or len(set(y[known].tolist())) < 2:
        return None
    held = np.zeros(len(y), bool)
    for k in (0, 1):
        held[np.flatnonzero(y == k)[::3]] = True
    train = (y >= 0) & ~held
    if len(set(y[train].tolist())) < 2:
        return None
    own = np.where(train, y, -1)
    truth, pseudo = s.counts(own, own), Counts.zero()
    ids = np.array(sorted(labels), np.int64)
    log = []
    for turn in range(rounds + 1):
        weights = Weights.fit(truth + pseudo)
        a, b = s.scores(weights)
        content_cal, meta_cal = logistic(a[held], y[held], 1e-3), logistic(b[held], y[held], 1e-3)
        if turn == rounds:
            break
        before, pseudo = pseudo, pool_counts(pool, ids, weights, content_cal, meta_cal, sure)
        log.append((int(pseudo.n_meta.sum()), int(pseudo.n_content.sum())))
        if np.array_equal(before.flat(), pseudo.flat()):
            break
    model = Model(weights, content_cal, meta_cal, np.zeros(3), 0.5, log)
    model.joint = logistic(np.c_[logit(prob(content_cal, a)), logit(prob(meta_cal, b))][held], y[held], 0.1)
    good = np.sort(model.probabilities(a, b)[2][held & (y == 1)])
    model.cut = float(np.clip(good[int(lost_good * len(good))], always_below, 0.5))
    return model


def fit(docs: DataFrame, labels: DataFrame, max_labelled: int = 3000, **how) -> Model | None:
    """Trains on a bounded sample of ``labels`` (doc_id, quality) and on all documents outside it, whose labels, if any, are not used."""
    known = labels.where("doc_id is not null and quality in (0, 1)").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    # Rejected documents are the rarer class, so each class fills half of the bound if it can.
    parts = [known.where(F.col("quality") == k).orderBy(F.xxhash64("doc_id")).limit(max_labelled // 2).collect() for k in (0, 1)]
    truth = {int(r.doc_id): int(r.quality) for part in parts for r in part}
    if not truth:
        return None
    spark = docs.sparkSession
    return cotrain(sample_features(docs, spark.createDataFrame([(i,) for i in sorted(truth)], "doc_id long")), truth, docs, **how)


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """Per row: doc_id, p_content, p_metadata, p_quality, kept.

    Null and empty texts are scored like others.  Without a model (no labels, or
    one class only) nothing is rejected and all probabilities are one.
    """
    schema = "doc_id long, p_content double, p_metadata double, p_quality double, kept boolean"
    if model is None:
        return docs.select(F.col("doc_id").cast("long").alias("doc_id"), *[F.lit(1.0).alias(c) for c in ("p_content", "p_metadata", "p_quality")], F.lit(True).alias("kept"))

    def run(batches: Iterator[pa.RecordBatch]):
        for batch in batches:
            for i in range(0, batch.num_rows, 512):
                part = batch.slice(i, 512)
                p = model.score(*rows_of(part))
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), *map(pa.array, p), pa.array(model.keeps(p[2]))], ["doc_id", "p_content", "p_metadata", "p_quality", "kept"])

    return prepared(docs).mapInArrow(lean(run), schema)


def prepared(docs: DataFrame) -> DataFrame:
    """The columns both views need; missing fields count as null."""
    has = set(docs.columns)
    kinds = {"source": "string", "lang": "string", "n_chars": "long"}
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", *[(F.col(c) if c in has else F.lit(None)).cast(k).alias(c) for c, k in kinds.items()])


def classify(docs: DataFrame, labels: DataFrame, **how) -> DataFrame:
    return score(docs, fit(prepared(docs), labels, **how))


def keep_good(docs: DataFrame, labels: DataFrame, **how) -> DataFrame:
    """The documents that are not rejected, with their own columns (of rows that repeat an id, all or none by their own text)."""
    model = fit(prepared(docs), labels, **how)
    if model is None:
        return docs
    names = docs.columns

    @F.pandas_udf("boolean")
    def kept(text, source, lang, n_chars):
        out = []
        for i in range(0, len(text), 512):
            texts = [t or "" for t in text[i : i + 512]]
            fields = [(s, g, None if n != n or n is None else int(n)) for s, g, n in zip(source[i : i + 512], lang[i : i + 512], n_chars[i : i + 512])]
            out.append(model.keeps(model.score(texts, fields)[2]))
        give_back()
        return text.__class__(np.concatenate(out) if out else [], dtype=bool)

    cols = [(F.col(c) if c in names else F.lit(None)).cast(k) for c, k in (("source", "string"), ("lang", "string"), ("n_chars", "long"))]
    return docs.withColumn("__kept", kept(F.col("text"), *cols)).where("__kept").select(*names)
