"""Toxicity by compression distance: two zstandard dictionaries, one of toxic and one of ordinary text.

Training uses a sample of at most SAMPLE_ROWS labelled rows, whole texts, counted in the executors.  Content that both classes
share is trained by zstandard on COMMON_WINDOWS windows; segments of one or two words whose document frequency differs between
the classes far beyond chance make up each class's own part.  (Dictionaries that zstandard's trainer alone makes of each class
don't tell them apart, as it prefers what is frequent in both; the README has the figures.)  A window that one dictionary
compresses to fewer bytes is closer to that class.  Scoring covers every window of every whole text; window differences become
four features, and a logistic curve fitted on sampled rows that the dictionaries haven't seen turns them into a score, with the
threshold at 0.5.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch, docs_of, kept_in_worker, map_batches, small_batches

WINDOW, STRIDE, LEVEL = 3, 2, 12
DICTIONARY_BYTES, OWN_SEGMENTS, LEAST_Z, LEAST_DOCS = 2048, 500, 4.0, 5
#: Bounds of the training sample, both drawn by hash: labelled rows, and windows of their texts for the shared content.
SAMPLE_ROWS, COMMON_WINDOWS = 4_000, 100_000
FOLDS, CLOSE = 5, 3


@dataclass
class Model:
    toxic: bytes
    ordinary: bytes
    weights: np.ndarray
    center: np.ndarray
    scale: np.ndarray


def windows(text: str, size: int = WINDOW, stride: int = STRIDE) -> list[bytes]:
    words = text.split()
    return [f" {' '.join(words[i : i + size])} ".encode() for i in range(0, max(1, len(words) - size + stride), stride)]


def _compressors(toxic: bytes, ordinary: bytes):
    out = []
    for content in (toxic, ordinary):
        held = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        held.precompute_compress(level=LEVEL)
        out.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=held, write_content_size=False, write_checksum=False, write_dict_id=False).compress)
    return out


def features(text: str, toxic, ordinary) -> list[float]:
    """Of the windows' differences in compressed bytes: share and number of clear ones, mean of the top three, total."""
    gain = np.array([len(ordinary(w)) - len(toxic(w)) for w in windows(text)], float)
    close = (gain >= CLOSE).sum()
    return [close / len(gain), math.log1p(close), float(np.sort(gain)[-3:].mean()), float(gain[gain > 0].sum() / math.sqrt(len(gain)))]


def _segments(text: str) -> set[str]:
    words = text.split()
    return {*words, *map(" ".join, zip(words, words[1:], strict=False))}


def dictionaries(sample: DataFrame) -> tuple[bytes, bytes]:
    """(toxic, ordinary) dictionary content from sample(text, toxic)."""
    spark = sample.sparkSession

    def segments(batch: pa.RecordBatch):
        for text, label in zip(batch.column("text"), batch.column("toxic").to_pylist(), strict=True):
            if own := sorted(_segments(text.as_py())):
                yield {"segment": own, "toxic": [label] * len(own)}

    def long_windows(batch: pa.RecordBatch):
        for text in batch.column("text"):
            yield {"window": windows(text.as_py(), 8, 4)}

    n = {r["toxic"]: r["n"] for r in sample.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    n1, n0 = max(1, n.get(1, 0)), max(1, n.get(0, 0))
    a, b = F.sum("toxic"), F.sum(1 - F.col("toxic"))
    counts = map_batches(sample, segments, segment="string", toxic="int").groupBy("segment").agg(a.alias("a"), b.alias("b")).where(F.col("a") + F.col("b") >= LEAST_DOCS)
    p = (F.col("a") + F.col("b")) / (n1 + n0)
    z = (F.col("a") / n1 - F.col("b") / n0) / F.sqrt(p * (1 - p) * (1 / n0 + 1 / n1) + 1e-12)
    counts = counts.select("segment", F.round(z, 9).alias("z"))
    own = [[r["segment"] for r in counts.where(F.col("z") * way > LEAST_Z).orderBy(F.col("z") * -way, "segment").limit(OWN_SEGMENTS).collect()] for way in (1, -1)]
    drawn = map_batches(sample, long_windows, window="binary").orderBy(F.xxhash64("window"), "window").limit(COMMON_WINDOWS)
    drawn = [bytes(r["window"]) for r in drawn.collect()]
    try:
        # what follows the header and the tables of the trained dictionary is its content; used raw, both sides share it
        common = zstandard.train_dictionary(DICTIONARY_BYTES, drawn).as_bytes()[512:]
    except zstandard.ZstdError:  # too little text to train on
        common = b"".join(drawn)[-DICTIONARY_BYTES:]
    toxic, ordinary = (common + b" " + " ".join(reversed(segments)).encode() + b" " for segments in own)
    return toxic, ordinary


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 50) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    center, scale = x.mean(0), x.std(0) + 1e-9
    design = np.c_[np.ones(len(x)), (x - center) / scale]
    w = np.zeros(design.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-design @ w))
        step = np.linalg.solve((design * (p * (1 - p))[:, None]).T @ design + ridge * np.eye(len(w)), design.T @ (y - p) - ridge * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w, center, scale


def train(sample: DataFrame) -> Model:
    """sample(doc_id, text, toxic 0 or 1), as training_rows gives it.  A quarter of the rows, by the id's crc32, calibrates, the
    others make the dictionaries; without rows in either part all rows do both.  Of an empty sample, every score is near 0, and
    of a single class, near that class."""
    scratch = Scratch(sample.sparkSession)
    sample = sample.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), F.col("toxic").cast("int").alias("toxic"))
    sample = scratch.save(sample.withColumn("late", F.crc32(F.concat(F.lit("calibrate:"), F.col("doc_id").cast("string"))) % 4 == 0), "sample")
    parts = {r["late"] for r in sample.select("late").distinct().collect()}
    own, rest = (sample.where("NOT late"), sample.where("late")) if len(parts) == 2 else (sample, sample)
    toxic, ordinary = dictionaries(own.select("text", "toxic"))
    if not parts:
        return Model(toxic, ordinary, np.array([-20.0, 0, 0, 0, 0]), np.zeros(4), np.ones(4))
    rows = np.array([[r["toxic"], r["f0"], r["f1"], r["f2"], r["f3"]] for r in _features(rest, toxic, ordinary, "doc_id", "toxic").orderBy("doc_id", "f0", "f1", "f2", "f3").collect()], float)
    return Model(toxic, ordinary, *_logistic(rows[:, 1:], rows[:, 0]))


def _features(docs: DataFrame, toxic: bytes, ordinary: bytes, *keys: str) -> DataFrame:
    """The keys and the four features f0..f3 of each text."""
    kinds = {"bigint": "long"}
    kinds = {k: kinds.get(v, v) for k, v in docs.select(*keys).dtypes}

    def step(batch: pa.RecordBatch):
        press = kept_in_worker(("toxicity", toxic, ordinary), lambda: _compressors(toxic, ordinary))
        x = np.array([features(t.as_py() or "", *press) for t in batch.column("text")]).reshape(-1, 4)
        yield {k: batch.column(k) for k in keys} | {f"f{i}": x[:, i] for i in range(4)}

    return map_batches(docs.select(*keys, F.col("text").cast("string")), step, **kinds, f0="double", f1="double", f2="double", f3="double")


def score(docs: DataFrame, model: Model) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, score, predicted).  Null and empty texts score like a text without any signal.
    Repeated ids give repeated rows; other columns are ignored."""
    small_batches(docs.sparkSession)
    x = _features(docs.select(F.col("doc_id").cast("long"), "text"), model.toxic, model.ordinary, "doc_id")  # two dictionaries of a few kilobytes travel with the job
    line = F.lit(float(model.weights[0]))
    for i, (w, c, s) in enumerate(zip(model.weights[1:], model.center, model.scale, strict=True)):
        line = line + (F.col(f"f{i}") - float(c)) / float(s) * float(w)
    p = 1 / (1 + F.exp(-F.greatest(F.least(line, F.lit(500.0)), F.lit(-500.0))))
    return x.select("doc_id", p.alias("score")).select("doc_id", "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def held_out(column: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(column).cast("string")) % FOLDS == 0, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """(doc_id, text, toxic): at most ``rows`` labelled documents outside the held-out fold; where there are more, those of
    the smallest hashes.  Of labels that contradict each other, toxic holds; of several texts of one id, the smallest."""
    usable = F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()
    named = labels.where(usable).groupBy("doc_id").agg(F.max((F.col("toxic") > 0).cast("int")).alias("toxic"))
    chosen = named.orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
    found = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")  # chosen has at most ``rows`` rows
    return found.groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted for every document; the model learns from labels outside the held-out fold."""
    docs = docs_of(spark, sf_dir)
    model = train(training_rows(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    return score(docs, model).select("doc_id", held_out().alias("held_out"), "score", "predicted")
