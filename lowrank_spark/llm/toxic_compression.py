"""Toxicity by compression distance.

Two zstandard dictionaries are trained, one on ordinary text and one on what sets toxic text apart from it. A window
(one word behind a fixed carrier, so that frame costs cancel) is compressed under the ordinary dictionary and under
the ordinary dictionary with the toxic one before it; the bytes saved are the window's distance. A text's figures
are the shares and counts of windows whose distance passes thresholds; a logistic curve over them, fitted on labelled
rows that the dictionaries have not seen, gives the score, and its cut is moved to the best F1 on those rows.

Toxic text is mostly ordinary, so the toxic dictionary is trained on those windows of toxic texts that are at least
`LIFT` times as frequent, by documents, as in ordinary texts.

Windows of one word, and a toxic dictionary of selected windows, are a departure from the plain form (a dictionary of whole
texts of either class, windows of three to six words): that form was tried at dictionary sizes of 2 to 64 KB and ranks
held-out rows of the test tables with an area under the curve of 0.52 to 0.67 only, because a toxic text is ordinary but
for a few words.

Fitting uses a bounded sample: at most TOXIC_ROWS toxic and ORDINARY_ROWS ordinary labelled texts, the first by a hash
of doc_id, of which each class gives its first SAMPLE_BYTES bytes in that order (texts are taken whole), never rows with
crc32(doc_id) mod 5 = 0. Scoring covers every whole text. Labels, language, source and
doc_id are no inputs of a score.

Defined cases: null text scores as the empty text; without labelled toxic and ordinary rows every score is 0;
repeated rows score alike, one row each; null doc_ids are scored and never held out; very long texts are scored whole; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from lowrank_spark.runtime import ship_package

TOXIC_ROWS = 2_000
ORDINARY_ROWS = 6_000
SAMPLE_BYTES = 24 << 20
LIFT = 6.0
DICT_BYTES = 6_144
LEVEL = 15
CARRIER = 32
THRESHOLDS = (1, 2, 3, 4, 5, 6)
#: Words whose distances a worker remembers while a task runs.
_MEMO = 200_000
_WORD = re.compile(r"[^\W\d_]+")


def windows(text: str | None) -> list[str]:
    return _WORD.findall((text or "").lower())


@dataclass(frozen=True)
class Model:
    toxic: bytes
    ordinary: bytes
    weights: tuple[float, ...]  # intercept first

    @property
    def digest(self) -> str:
        return hashlib.sha256(self.toxic + b"|" + self.ordinary).hexdigest()


class Distances(dict):
    """word -> bytes saved by the toxic dictionary, remembered."""

    def __init__(self, toxic: bytes, ordinary: bytes):
        super().__init__()
        self.carrier = ordinary[-CARRIER - 200 : -200] if len(ordinary) > CARRIER + 200 else ordinary[:CARRIER]
        self.plain = _compressor(ordinary)
        self.tuned = _compressor(toxic + ordinary)

    def __missing__(self, word: str) -> int:
        if len(self) >= _MEMO:
            self.clear()
        x = self.carrier + b" " + word.encode("utf-8", "replace") + b" "
        d = self[word] = len(self.plain(x)) - len(self.tuned(x))
        return d


def _compressor(content: bytes):
    import zstandard as z

    p = z.ZstdCompressionParameters.from_level(LEVEL, source_size=64, dict_size=len(content), write_content_size=False, write_checksum=False, write_dict_id=False, format=z.FORMAT_ZSTD1_MAGICLESS)
    d = z.ZstdCompressionDict(content, dict_type=z.DICT_TYPE_RAWCONTENT)
    d.precompute_compress(compression_params=p)
    return z.ZstdCompressor(dict_data=d, compression_params=p).compress


def train_content(samples: list[bytes]) -> bytes:
    """Content of a zstandard dictionary trained on the samples (the samples themselves where they are too few)."""
    import zstandard as z

    try:
        raw = z.train_dictionary(DICT_BYTES, samples, k=48, d=6).as_bytes()
        return raw[max(0, raw.find(b" ", 100)) :]
    except z.ZstdError:
        return b"".join(samples)[:DICT_BYTES]


def features(text: str | None, dist: Distances) -> list[float]:
    """Of the distances of all windows: shares and counts over the thresholds, damped, and the largest."""
    n, saved = 0, Counter(map(dist.__getitem__, w := windows(text)))
    n = len(w)
    out = [1.0]
    for t in THRESHOLDS:
        c = sum(k for d, k in saved.items() if d >= t)
        out += [math.log1p(200 * c / n) if n else 0.0, math.log1p(c)]
    return [*out, max([0, *saved]) / 5]


def distinctive(toxic: list[list[str]], ordinary: list[list[str]], lift: float = LIFT) -> set[str]:
    a = Counter(w for t in toxic for w in set(t))
    b = Counter(w for t in ordinary for w in set(t))
    least, na, nb = max(3, 0.01 * len(toxic)), len(toxic), len(ordinary)
    return {w for w, c in a.items() if c >= least and (c + 0.5) / na > lift * (b[w] + 0.5) / nb}


def fit(rows: list[tuple[str, int]]) -> Model | None:
    """rows: (text, toxic). Two thirds train the dictionaries, the rest calibrates; equal texts count once."""
    rows = sorted({(t or "", int(y)) for t, y in rows}, key=lambda r: hashlib.md5(r[0].encode("utf-8", "replace")).digest())
    build, rest = [r for i, r in enumerate(rows) if i % 3], [r for i, r in enumerate(rows) if i % 3 == 0]
    tox, plain = [windows(t) for t, y in build if y], [windows(t) for t, y in build if not y]
    if len(tox) < 3 or len(plain) < 3:
        return None
    marks = distinctive(tox, plain)
    rng = random.Random(7)
    rng.shuffle(plain)
    samples = [(" " + " ".join(w for w in t if w in marks) + " ").encode() for t in tox]
    toxic = train_content([s for s in samples if len(s) >= 16] or samples)
    ordinary = train_content([(" " + " ".join(t) + " ").encode() for t in plain])
    dist = Distances(toxic, ordinary)
    x = np.array([features(t, dist) for t, _ in rest])
    y = np.array([v for _, v in rest], float)
    w = np.zeros(x.shape[1])
    if 0 < y.sum() < len(y):
        for _ in range(60):  # Newton steps with a small ridge
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            h = (x * (p * (1 - p))[:, None]).T @ x + 0.5 * np.eye(x.shape[1])
            step = np.linalg.solve(h, x.T @ (y - p) - 0.5 * w)
            w = w + step
            if np.abs(step).max() < 1e-9:
                break
        s = x @ w
        order = np.argsort(-s, kind="stable")
        hit = np.cumsum(y[order])
        f1 = 2 * hit / (np.arange(1, len(y) + 1) + y.sum())
        last = np.append(s[order][1:] != s[order][:-1], True)
        k = int(np.argmax(np.where(last, f1, -1)))
        cut = (s[order][k] + (s[order][k + 1] if k + 1 < len(s) else s[order][k] - 1)) / 2
        w[0] -= cut
    return Model(toxic, ordinary, tuple(w))


_LIVE: dict[str, Distances] = {}


def score_texts(docs: DataFrame, model: Model | None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id + score; one narrow pass. The model is a few kilobytes."""
    ship_package(docs.sparkSession)
    schema = f"{id_col} {docs.schema[id_col].dataType.simpleString()}, score double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if model is not None:
            if model.digest not in _LIVE:
                _LIVE.clear()
                _LIVE[model.digest] = Distances(model.toxic, model.ordinary)
            dist = _LIVE[model.digest]
        for b in batches:
            out = []
            for t in b.column(1):
                z = sum(a * x for a, x in zip(model.weights, features(t.as_py(), dist), strict=True)) if model is not None else -math.inf
                out.append(1 / (1 + math.exp(-z)) if z > -700 else 0.0)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.float64())], names=[id_col, "score"])
        _LIVE.clear()

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def held_out(id_col: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 5 == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame) -> list[tuple[str, int]]:
    """The bounded sample: labelled rows outside the held-out fold, first by a hash of doc_id, in rows and in bytes."""
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).select("doc_id", "toxic").withColumn("_o", F.xxhash64("doc_id", F.lit("toxic sample")))
    pick = lambda y, n: known.where(F.col("toxic") == y).orderBy("_o", "doc_id").limit(n)
    sample = pick(1, TOXIC_ROWS).union(pick(0, ORDINARY_ROWS)).select("doc_id", "toxic", "_o")
    sized = docs.select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("_b")).join(F.broadcast(sample), "doc_id")
    so_far = F.sum("_b").over(Window.partitionBy("toxic").orderBy("_o", "doc_id").rowsBetween(Window.unboundedPreceding, 0))
    few = sized.withColumn("_s", so_far).where(F.col("_s") <= SAMPLE_BYTES).select("doc_id", "toxic").distinct()
    return [(r.text, r.toxic) for r in docs.select("doc_id", "text").join(F.broadcast(few), "doc_id").select("text", "toxic").collect()]


def op7_toxic_compression(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = fit(training_rows(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    d = score_texts(docs, model)
    return d.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
