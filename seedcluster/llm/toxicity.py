"""A counterfactual-regularised toxicity classifier over hashed words and word heads.

Logistic regression on the distinct words of a text. In training, every text has a counterfactual twin in which identity terms
are swapped for other ones (a text without any gets one in place of a word), and the squared change of its log-odds is penalised,
so that naming a group does not move a score. Null, empty and wordless texts get the score of the bias alone; repeated
rows are scored each; labels that are null, or differ for one document, are left out of training; an empty training set
gives one constant score.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CODES, chunks, lean, mix64, ready, spans_hash, utf8, word_spans, written

BITS = 18
#: Names of groups, by kind, in the languages of the texts (word list; a swap stays within a kind).
IDENTITY = (
    ("women", "men", "girls", "boys", "mujeres", "hombres", "femmes", "hommes", "frauen", "männer"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists", "musulmanes", "cristianos", "judíos", "musulmans", "chrétiens", "juifs", "muslime", "christen", "juden"),
    ("gay", "straight", "lesbian", "transgender", "homosexuales", "homosexuels", "schwule"),
    ("black", "white", "asian", "latino", "african", "european", "arab", "negros", "blancos", "noirs", "blancs", "schwarze", "weiße"),
    ("immigrants", "refugees", "foreigners", "natives", "inmigrantes", "refugiados", "immigrés", "réfugiés", "einwanderer", "flüchtlinge"),
    ("disabled", "blind", "deaf", "old", "young", "elderly"),
)
TRIMMED = np.zeros(256, bool)
TRIMMED[[c for c in range(33, 127) if not chr(c).isalnum()]] = True


def features(column: pa.Array, bits: int = BITS) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """(first row, rows, row of each feature, feature) by chunks; a feature is counted once a text. Words lose punctuation at their ends."""
    raw, offsets = utf8(pc.utf8_lower(column.cast(pa.large_string())))
    for a, b in chunks(np.diff(offsets)):
        part, off = raw[offsets[a] : offsets[b]], offsets[a : b + 1] - offsets[a]
        starts, ends, row = word_spans(part, off)
        for _ in range(3):
            full = ends > starts
            starts = starts + (full & TRIMMED[part[np.minimum(starts, len(part) - 1)]]) if len(part) else starts
            full = ends > starts
            ends = ends - (full & TRIMMED[part[np.maximum(ends - 1, 0)]]) if len(part) else ends
        full = ends > starts
        starts, ends, row = starts[full], ends[full], row[full]
        if not len(starts):
            yield a, b - a, np.zeros(0, np.int64), np.zeros(0, np.int64)
            continue
        codes = CODES[part]
        word = spans_hash(codes, starts, ends)
        heads = [spans_hash(codes, starts, np.minimum(starts + k, ends)) ^ np.uint64(k) for k in HEADS]
        keep = [ends - starts > k for k in HEADS]
        f = np.concatenate([word, *(mix64(h[k]) for h, k in zip(heads, keep, strict=True))]) >> np.uint64(64 - bits)
        r = np.concatenate([row, *(row[k] for k in keep)])
        key = np.unique(r.astype(np.uint64) << np.uint64(bits) | f)
        yield a, b - a, (key >> np.uint64(bits)).astype(np.int64), (key & np.uint64((1 << bits) - 1)).astype(np.int64)


#: Bytes at the head of a word that make a feature of their own.
HEADS = (4, 5, 6)


def word_features(word: str, bits: int = BITS) -> np.ndarray:
    return next(features(pa.array([word]), bits))[3]


def word_key(word: str, bits: int = BITS) -> int:
    """The feature of the whole word, which its longer relatives lack."""
    raw = np.frombuffer(word.lower().encode(), np.uint8)
    return int(spans_hash(CODES[raw], np.zeros(1, np.int64), np.array([len(raw)]))[0] >> np.uint64(64 - bits))


def identity_features(bits: int = BITS) -> np.ndarray:
    """All features of the identity terms."""
    return np.unique(np.concatenate([word_features(x, bits) for kind in IDENTITY for x in kind]))


def telling(one: np.ndarray, every: np.ndarray, n1: float, n: float, z: float) -> np.ndarray:
    """Whether a feature's share among texts of label 1 differs from that among the others by z standard errors and it is in three texts.

    one, every: texts of label 1, and all texts, that have the feature; n1 of n texts have label 1.
    """
    p = (every + 1) / (n + 2)
    error = np.sqrt(p * (1 - p) * (1 / n1 + 1 / (n - n1)))
    return (np.abs(one / n1 - (every - one) / (n - n1)) >= z * error) & (every >= 3)


def train(texts: list[np.ndarray], labels: np.ndarray, bits: int = BITS, epochs: int = 20, rate: float = 0.2, l2: float = 1e-5, counterfactual: float = 1.0, positive: float = 2.5, seed: int = 5) -> tuple[np.ndarray, float]:
    """Weights and bias from the texts' features, which fit() has cut to the telling ones and those of identity terms. Adagrad over small batches."""
    n = len(texts)
    w, b = np.zeros(1 << bits), 0.0
    if not n or labels.min() == labels.max():
        p = (labels.sum() + 0.5) / (n + 1)
        return w, float(np.log(p / (1 - p)))
    rng = np.random.default_rng(seed)
    kinds = [[word_features(x, bits) for x in kind] for kind in IDENTITY]
    own = [(k, i) for k, kind in enumerate(kinds) for i in range(len(kind))]
    main: dict[int, list[tuple[int, int]]] = {}
    for k, i in own:
        main.setdefault(word_key(IDENTITY[k][i], bits), []).append((k, i))
    keys = np.array(sorted(main))
    named = [[x for key in t[np.isin(t, keys)].tolist() for x in main[key]] for t in texts]
    g2, gb = np.full(1 << bits, 1e-6), 1e-6
    size = np.array([len(x) for x in texts])
    b = float(np.log((labels.sum() + 0.5) / (n - labels.sum() + 0.5)))
    for _ in range(epochs):
        order = rng.permutation(n)
        for at in range(0, n, 128):
            pick = order[at : at + 128]
            f, row = np.concatenate([texts[i] for i in pick]), np.repeat(np.arange(len(pick)), size[pick])
            slope = 1 / (1 + np.exp(-np.clip(np.bincount(row, w[f], len(pick)) + b, -30, 30))) - labels[pick]
            slope = np.where(labels[pick] == 1, positive * slope, slope)
            idx, grad = [f], [slope[row] / len(pick)]
            for i in pick.tolist():
                # The twin: one identity term for another of its kind, or one put in where there is none.
                k, old = named[i][rng.integers(len(named[i]))] if named[i] else (int(rng.integers(len(kinds))), None)
                to = kinds[k][rng.integers(len(kinds[k]))]
                gone = kinds[k][old] if old is not None else to[:0]
                change = w[to].sum() - w[gone].sum()
                if change:
                    idx += [to, gone]
                    grad += [np.full(len(to), 2 * counterfactual * change / len(pick)), np.full(len(gone), -2 * counterfactual * change / len(pick))]
            used, back = np.unique(np.concatenate(idx), return_inverse=True)
            g = np.bincount(back, np.concatenate(grad), len(used)) + l2 * w[used]
            g2[used] += g * g
            w[used] -= rate * g / np.sqrt(g2[used])
            gb += slope.mean() ** 2
            b -= rate * slope.mean() / np.sqrt(gb)
    return w, b


def held_out(doc_id: str = "doc_id"):
    """Whether crc32 of the id as text leaves 1 modulo 3."""
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 3 == 1


def fit(docs: DataFrame, labels: DataFrame, most: int = 20_000, doc_id: str = "doc_id", text: str = "text", label: str = "toxic", bits: int = BITS, counterfactual: float = 1.0, z: float = 5.0) -> tuple[np.ndarray, float]:
    """Trains on the at most `most` labelled documents, not held out, that come first by a hash of doc_id.

    Spark counts each feature by label and chooses the telling ones; of the documents, only those and the identity terms' reach the driver.
    Of rows with one id the least text counts.
    """
    spark = ready(docs.sparkSession)
    names = ["doc_id", "label", "features"]

    def hashed(batches):
        for batch in batches:
            for a, rows, row, f in features(batch.column(2), bits):
                at = np.searchsorted(row, np.arange(rows + 1))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, rows), batch.column(1).slice(a, rows), pa.array([f[i:j].astype("<i4").tobytes() for i, j in zip(at, at[1:], strict=False)], pa.binary())], names)

    def counted(batches):
        every, one = np.zeros(1 << bits, np.int64), np.zeros(1 << bits, np.int64)
        for batch in batches:
            for y, x in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                f = np.frombuffer(x, "<i4")
                every[f] += 1
                one[f] += y
        f = np.flatnonzero(every)
        yield pa.RecordBatch.from_arrays([pa.array(f), pa.array(one[f]), pa.array(every[f])], ["f", "one", "every"])

    known = labels.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(label).cast("int").alias("label")).where("label IN (0, 1) AND doc_id IS NOT NULL").groupBy("doc_id").agg(F.min("label").alias("label"), F.max("label").alias("other")).where("label = other").drop("other")
    known = known.where(~held_out()).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).join(F.broadcast(known), "doc_id").groupBy("doc_id", "label").agg(F.min("text").alias("text"))
    sample = written(rows.mapInArrow(lean(hashed), "doc_id long, label int, features binary"), "labelled")
    n, n1 = sample.agg(F.count(F.lit(1)), F.coalesce(F.sum("label"), F.lit(0))).first()
    if n in (0, n1) or not n1:
        return train([np.zeros(0, np.int64)] * n, np.full(n, float(n1 > 0)), bits)
    counts = sample.mapInArrow(lean(counted), "f long, one long, every long").groupBy("f").agg(F.sum("one").alias("one"), F.sum("every").alias("every")).where("every >= 3").toPandas()
    use = np.zeros(1 << bits, bool)
    use[counts["f"].to_numpy()[telling(counts["one"].to_numpy(), counts["every"].to_numpy(), n1, n, z)]] = True
    use[identity_features(bits)] = True
    sent = spark.sparkContext.broadcast(use)

    def chosen(batches):
        for batch in batches:
            got = [np.frombuffer(x, "<i4") for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([f[sent.value[f]].tobytes() for f in got], pa.binary())], names)

    got = sample.mapInArrow(lean(chosen), "doc_id long, label int, features binary").orderBy("doc_id").toArrow()
    return train([np.frombuffer(x, "<i4") for x in got.column("features").to_pylist()], got.column("label").to_numpy().astype(float), bits, counterfactual=counterfactual)


def scored(docs: DataFrame, model: tuple[np.ndarray, float], threshold: float = 0.7, doc_id: str = "doc_id", text: str = "text", bits: int = BITS) -> DataFrame:
    """(doc_id, score, predicted) of every whole text. The model is 2**bits numbers, whatever the corpus."""
    spark = ready(docs.sparkSession)
    sent = spark.sparkContext.broadcast((model[0].astype(np.float32), float(model[1])))

    def run(batches):
        w, b = sent.value
        for batch in batches:
            for a, rows, row, f in features(batch.column(1), bits):
                z = np.bincount(row, w[f], rows) + b
                score = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, rows), pa.array(score), pa.array((score >= threshold).astype(np.int32))], ["doc_id", "score", "predicted"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(lean(run), "doc_id long, score double, predicted int")


def without_toxic(docs: DataFrame, model: tuple[np.ndarray, float], threshold: float = 0.7, text: str = "text", bits: int = BITS) -> DataFrame:
    """docs, all columns as they are, less the rows whose text scores `threshold` or more."""
    spark = ready(docs.sparkSession)
    sent = spark.sparkContext.broadcast((model[0].astype(np.float32), float(model[1])))
    at = docs.columns.index(text)

    def run(batches):
        w, b = sent.value
        for batch in batches:
            good = np.ones(batch.num_rows, bool)
            for a, rows, row, f in features(batch.column(at), bits):
                z = np.bincount(row, w[f], rows) + b
                good[a : a + rows] = 1 / (1 + np.exp(-np.clip(z, -30, 30))) < threshold
            yield batch.filter(pa.array(good))

    return docs.mapInArrow(lean(run), docs.schema)


def is_held_out(doc_id: int) -> bool:
    return zlib.crc32(str(doc_id).encode()) % 3 == 1
