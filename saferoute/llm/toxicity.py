"""Toxicity by compression distance: which of two zstandard dictionaries shortens a text's windows.

Training takes a bounded sample of labelled rows, those whose crc32 of the id is not 2 modulo 4. One
dictionary is trained on windows of ordinary texts; the other on what sets toxic texts apart: words cut
to the longest beginning that is much more frequent in toxic texts than in ordinary ones. The toxic side
compresses with both, the ordinary side with the ordinary one alone, so the two lengths of a window
differ only by what toxic texts add. The beginnings of words are written in flipped bytes, so that a word's
beginning matches beginnings only, and windows start with a fixed anchor that both dictionaries hold, so
that short windows are not stored raw.

Dictionaries trained on whole windows of both kinds were tried and don't tell them apart: a toxic text is
mostly ordinary words, and both dictionaries then learn those. Over sf0.1 they find 9 to 16 % of the held-out
toxic texts at 3 to 5 % false alarms, against 84 % at 1.4 % for what is built here.

The distances of a text's windows (its largest three, their mean, how many exceed ``FAR``) are
calibrated to a probability by logistic regression on the same training rows.

Nulls and empty texts have no windows and get the score of a text without signs. Without labels of both
kinds every score is 0. Repeated rows get equal rows. Labels, lang, source and ids are never inputs.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Bounds of the training sample: toxic and ordinary rows.
TOXIC_ROWS, ORDINARY_ROWS = 2500, 5000
#: About so many windows of ordinary texts train the ordinary dictionary.
ORDINARY_WINDOWS = 60_000
#: Words in a window; bytes of the two dictionaries; bytes from which a distance is large.
WINDOW, TOXIC_BYTES, ORDINARY_BYTES, FAR = 4, 1024, 8192, 4
#: Share of toxic training texts that a beginning must occur in, and how many times the ordinary share.
LEAST_SHARE, LEAST_RATIO = 0.02, 15
PREDICT = 0.3
WORDS = re.compile(rb"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")
_FLIP = bytes(b ^ 0x20 for b in range(256))
ANCHOR = bytes(range(128, 168))


def held_out(doc_id: object) -> bool:
    return zlib.crc32(str(doc_id).encode()) % 4 == 2


def words(text: str | None) -> list[bytes]:
    return WORDS.findall((text or "").lower().encode("utf-8", "replace"))


def marked(word: bytes) -> bytes:
    return word[:5].translate(_FLIP) + word[5:]


def windows(text: str | None, size: int = WINDOW) -> list[bytes]:
    w = [x[:5].translate(_FLIP) + x[5:] for x in words(text)]
    return [ANCHOR + b" ".join(w[i : i + size]) for i in range(0, len(w), size)]


def beginnings(word: bytes) -> list[bytes]:
    b = b" " + word + b" "
    return [b[:n] for n in range(5, min(len(b), 12) + 1)]


def telling(toxic: list[str], ordinary: list[str]) -> set[bytes]:
    """The beginnings of words that set toxic texts apart, by the share of texts they occur in."""

    def counted(texts: list[str]) -> Counter:
        return Counter(g for t in texts for g in {g for w in set(words(t)) for g in beginnings(w)})

    a, b = counted(toxic), counted(ordinary)
    return {g for g, n in a.items() if n >= max(2, LEAST_SHARE * len(toxic)) and (n + 0.5) / len(toxic) > LEAST_RATIO * (b[g] + 0.5) / len(ordinary)}


def _trained(size: int, samples: list[bytes], **options) -> bytes:
    """A trained dictionary's bytes; where there is too little to train on, the samples themselves."""
    try:
        return zstandard.train_dictionary(size, samples, **options).as_bytes()
    except zstandard.ZstdError:
        return b" ".join(samples)[-size:]


class Judge:
    """Both compressors and the calibration; built on each worker from plain bytes."""

    def __init__(self, toxic: bytes, ordinary: bytes, weights: np.ndarray | None) -> None:
        options = zstandard.ZstdCompressionParameters(window_log=15, hash_log=16, chain_log=15, search_log=6, min_match=4, target_length=32, strategy=3, write_content_size=False, write_checksum=False, write_dict_id=False)
        self.weights = weights
        self.sides = []
        for content in (ordinary + ANCHOR, toxic + ordinary + ANCHOR):
            d = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            d.precompute_compress(compression_params=options)
            self.sides.append(zstandard.ZstdCompressor(compression_params=options, dict_data=d))

    def distances(self, text: str | None) -> np.ndarray:
        ordinary, toxic = self.sides[0].compress, self.sides[1].compress
        return np.array([len(ordinary(x)) - len(toxic(x)) for x in windows(text)], np.int64)

    def signs(self, text: str | None) -> tuple:
        d = np.concatenate([self.distances(text), np.zeros(3, np.int64)])
        top = np.sort(np.partition(d, len(d) - 3)[-3:])[::-1]
        far = int((d >= FAR).sum())
        return 1.0, *np.minimum(top, 12), np.log1p(far), min(far / len(d), 0.5) * 10, float(np.clip(d.mean(), -1, 2))

    def scores(self, texts: list[str | None]) -> np.ndarray:
        if self.weights is None:
            return np.zeros(len(texts))
        x = np.array([self.signs(t) for t in texts]).reshape(len(texts), len(self.weights))
        return 1 / (1 + np.exp(-np.clip(x @ self.weights, -30, 30)))


def logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 0.01, rounds: int = 30) -> np.ndarray:
    """Weights by Newton's method over weighted rows."""
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w = w + np.linalg.solve((x * (weight * p * (1 - p) + 1e-9)[:, None]).T @ x + ridge * np.eye(len(w)), x.T @ (weight * (y - p)) - ridge * w)
    return w


def train(toxic: list[str], ordinary: list[str], ratio: float | None = None) -> tuple[bytes, bytes, np.ndarray | None]:
    """Toxic dictionary, ordinary dictionary and calibration; what ``Judge`` takes.

    ``ratio``: ordinary rows for each toxic one among all labels, where the sample has others."""
    if not toxic or not ordinary:
        return b"", b"", None
    keep = telling(toxic, ordinary)

    def cut(word: bytes) -> bytes | None:
        b = b" " + word + b" "
        g = max((g for g in beginnings(word) if g in keep), key=len, default=None)
        return None if g is None else marked(g[1:].strip()) + (b" " if g == b else b"")

    pieces = [b" ".join(c for c in map(cut, words(t)) if c) for t in toxic]
    pieces = [x for x in pieces if len(x) > 4]
    plain = [x[len(ANCHOR) :] for t in ordinary for x in windows(t, 2 * WINDOW)]
    every = -(-len(plain) // ORDINARY_WINDOWS)  # a sample of all of them by their hashes
    plain = [x for x in plain if zlib.crc32(x) % every == 0]
    first = _trained(TOXIC_BYTES, pieces * 5, k=64, d=6) if pieces else b""
    second = _trained(ORDINARY_BYTES, plain) if plain else b""
    judge = Judge(first, second, None)
    x = np.array([judge.signs(t) for t in toxic + ordinary])
    y = np.repeat([1, 0], [len(toxic), len(ordinary)])
    weight = np.where(y == 1, 1.0, (ratio or len(ordinary) / len(toxic)) * len(toxic) / len(ordinary))
    return first, second, logistic(x, y, weight)


def sample(docs: DataFrame, labels: DataFrame, toxic_rows: int = TOXIC_ROWS, ordinary_rows: int = ORDINARY_ROWS) -> tuple[list[str], list[str], float]:
    """Texts of at most so many toxic and ordinary labelled rows, held-out rows excepted, by a hash of the id;
    and the ordinary rows for each toxic one among all these labels.

    The ids are chosen first, from the labels alone; only their texts are then read and collected, one for each id."""
    left = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & (F.crc32(F.col("doc_id").cast("string")) % 4 != 2)).select("doc_id", "toxic").distinct()
    chosen = common.lowest(left.where("toxic = 1"), "doc_id", toxic_rows).unionAll(common.lowest(left.where("toxic = 0"), "doc_id", ordinary_rows))
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id").groupBy("doc_id", "toxic").agg(F.min(F.coalesce("text", F.lit(""))).alias("text")).toPandas()
    rows = rows.sort_values(["doc_id", "text"], kind="stable")
    n = {r["toxic"]: r["count"] for r in left.groupBy("toxic").count().collect()}
    return list(rows.text[rows.toxic == 1]), list(rows.text[rows.toxic == 0]), n.get(0, 0) / max(1, n.get(1, 0))


def score(docs: DataFrame, model: tuple) -> DataFrame:
    """doc_id and score of every row; the model is a few kilobytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Judge(*model)
        for b in (whole.slice(i, 500) for whole in batches for i in range(0, whole.num_rows, 500)):
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(judge.scores(b.column("text").to_pylist()), pa.float64())], ["doc_id", "score"])
        common.trim()

    return common.over_batches(docs.select("doc_id", "text"), run, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, score double")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "labels")
    model = train(*sample(docs, labels))
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 4 == 2, F.lit(False))
    return score(docs, model).select("doc_id", held.alias("held_out"), "score", F.when(F.col("score") >= PREDICT, 1).otherwise(0).alias("predicted"))
