"""Quality rules: per-document rule statistics judged by an isolation forest.

``statistics`` computes the rule statistics of every whole text in one pass. ``fit_forest`` grows
random-split trees, of bounded depth, on all labelled good rows of one half, ``calibrate`` sets the score above
which a row counts as anomalous from labelled rows, and ``score`` adds the anomaly score.

Nulls and empty texts: every statistic is 0; such rows fail the word-count rule. Null labels are
not used. Without labels of both kinds no row is judged anomalous. Repeated rows get equal rows
back; columns other than ``doc_id`` and ``text`` are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

TREES, SUBSAMPLE = 128, 256
#: Least width, beside a node's range, from which cuts are drawn (the statistics are ratios).
MARGIN = 0.05
#: Share of labelled good rows that the threshold may reject.
GOOD_LOSS = 0.002
MIN_WORDS, REPEAT_PERCENT = 10, 20
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
FEATURES = ("word_length", "symbols", "dup_lines", "repeats", "upper", "marks", "digits", "distinct", "top_word", "shout", "line_ends", "letters")
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\v\f\r"
_MIX = np.uint64(0x9E3779B97F4A7C15)


def repeated_words(words: list[bytes], width: int = 5) -> int:
    """Words that lie in a window of ``width`` words found twice or more."""
    n = len(words) - width + 1
    if n < 2:
        return 0
    code = {w: i for i, w in enumerate(dict.fromkeys(words))}
    if len(code) == len(words):
        return 0
    ids = np.fromiter(map(code.__getitem__, words), dtype=np.uint64, count=len(words))
    if len(code) < 8000:  # five codes of 13 bits fit in 64 bits without loss up to 2**12.8 words
        mixed = np.zeros(n, np.uint64)
        base = np.uint64(len(code))
        for k in range(width):
            mixed = mixed * base + ids[k : k + n]
        if len(code) ** width >= 2**64:
            mixed = None
    else:
        mixed = None
    if mixed is None:
        _, mixed = np.unique(np.lib.stride_tricks.sliding_window_view(ids, width), axis=0, return_inverse=True)
        mixed = mixed.ravel()
    order = np.argsort(mixed, kind="stable")
    s = mixed[order]
    same = s[1:] == s[:-1]
    if not same.any():
        return 0
    hit = np.zeros(n, bool)
    hit[order[1:][same]] = True
    hit[order[:-1][same]] = True
    edge = np.zeros(len(words) + 1, np.int32)
    at = np.flatnonzero(hit)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + width, -1)
    return int((np.cumsum(edge)[:-1] > 0).sum())


def measure(text: str | None) -> tuple:
    """COUNTS then FEATURES of one text."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    n = len(words)
    chars = len(text) - sum(map(text.count, SPACES))
    symbols = sum(map(text.count, SYMBOLS))
    seen: set[bytes] = set()
    lines = dup = ended = 0
    for line in raw.split(b"\n"):
        if line and (body := line.strip()):
            lines += 1
            dup += line in seen
            seen.add(line)
            ended += body[-1:] in b".!?"
    repeats = repeated_words(words)
    if not n:
        return (0,) * len(COUNTS) + (0.0,) * len(FEATURES)
    deleted = len(raw)
    upper = deleted - len(raw.translate(None, b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"))
    digits = deleted - len(raw.translate(None, b"0123456789"))
    marks = deleted - len(raw.translate(None, b"!?;:()[]{}\"'_=+/\\~^@`"))
    ascii_marks = deleted - len(raw.translate(None, b".,-")) + marks + digits + symbols
    counts = Counter(words)
    return (n, chars, symbols, dup, repeats, chars / n, symbols / n, dup / max(1, lines), repeats / n, upper / chars, marks / n, digits / chars,
            len(counts) / n ** 0.8, counts.most_common(1)[0][1] / n, text.count("!") / n, ended / max(1, lines), 1 - ascii_marks / chars)


def statistics(docs: DataFrame) -> DataFrame:
    """doc_id, the rule counts (long) and the features (double) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = COUNTS + FEATURES
        kinds = [pa.int64()] * len(COUNTS) + [pa.float64()] * len(FEATURES)
        for b in batches:
            rows = list(zip(*map(measure, b.column("text").to_pylist()), strict=True)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *(pa.array(c, k) for c, k in zip(rows, kinds, strict=True))], ["doc_id", *names])
        common.trim()

    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, " + ", ".join(f"{c} long" for c in COUNTS) + ", " + ", ".join(f"{c} double" for c in FEATURES)
    return common.over_batches(docs.select("doc_id", "text"), run, schema)


def _average_path(n: np.ndarray | float) -> np.ndarray | float:
    """Mean depth of an unsuccessful search in a binary tree of n keys."""
    n = np.maximum(n, 1)
    return np.where(n > 2, 2 * (np.log(np.maximum(n - 1, 1)) + 0.5772156649) - 2 * (n - 1) / n, np.where(n == 2, 1.0, 0.0))


def fit_forest(rows: np.ndarray, trees: int = TREES, subsample: int = SUBSAMPLE, seed: int = 42, depth_limit: int | None = None) -> dict[str, np.ndarray]:
    """Trees of random splits as flat arrays; a leaf has feature -1 and its path length in ``cut``.

    Cuts are drawn from the node's range widened by a quarter and by ``MARGIN`` on both sides, also
    where the sample has a single value, so that a row beyond anything seen is split off early."""
    rng = np.random.default_rng(seed)
    depth_limit = depth_limit or math.ceil(math.log2(max(2, subsample))) + 4
    out: dict[str, list] = {"feature": [], "cut": [], "left": [], "right": [], "root": []}

    def add(f: int, c: float) -> int:
        for k, v in (("feature", f), ("cut", c), ("left", 0), ("right", 0)):
            out[k].append(v)
        return len(out["cut"]) - 1

    def grow(x: np.ndarray, depth: int) -> int:
        low, high = x.min(0), x.max(0)
        if len(x) <= 1 or depth >= depth_limit:
            return add(-1, depth + float(_average_path(float(len(x)))))
        f = int(rng.integers(x.shape[1]))
        wide = (high[f] - low[f]) / 4 + MARGIN
        cut = rng.uniform(low[f] - wide, high[f] + wide)
        node = add(f, cut)
        below = x[:, f] < cut
        for side, part in (("left", x[below]), ("right", x[~below])):
            child = grow(part, depth + 1) if len(part) else add(-1, float(depth + 1))
            out[side][node] = child
        return node

    for _ in range(trees if len(rows) else 0):
        out["root"].append(grow(rows[rng.choice(len(rows), min(subsample, len(rows)), replace=False)], 0))
    forest = {k: np.array(v, np.float64 if k == "cut" else np.int64) for k, v in out.items()}
    return forest | {"norm": np.array(float(_average_path(float(min(subsample, max(2, len(rows)))))))}


def anomaly(forest: dict[str, np.ndarray], x: np.ndarray) -> np.ndarray:
    """2 ** (-mean path length / expected path length): near 1 for anomalies."""
    if not len(forest["root"]):
        return np.zeros(len(x))
    at = np.broadcast_to(forest["root"], (len(x), len(forest["root"]))).copy()
    rows = np.arange(len(x))[:, None]
    while True:
        f = forest["feature"][at]
        inner = f >= 0
        if not inner.any():
            break
        step = np.where(x[rows, np.maximum(f, 0)] < forest["cut"][at], forest["left"][at], forest["right"][at])
        at = np.where(inner, step, at)
    return np.exp2(-forest["cut"][at].mean(1) / max(1e-9, float(forest["norm"])))


def calibrate(scores: np.ndarray, good: np.ndarray, good_loss: float = GOOD_LOSS) -> float:
    """The score above which a row is anomalous: the best gap among cuts that lose few good rows."""
    if not good.any() or good.all():
        return float("inf")
    least = np.quantile(scores[good], 1 - good_loss, method="higher")
    top = np.sort(scores[~good & (scores > least)])
    return float((least + top[0]) / 2) if len(top) else float(least)


def grow_forest(rows: DataFrame, trees: int = TREES, subsample: int = SUBSAMPLE) -> dict[str, np.ndarray]:
    """``fit_forest`` over all rows (doc_id, FEATURES), a tree in a task: each row goes to one tree at least, by hashes, and to as many
    as leave a tree about ``subsample`` rows. With more rows trees see more; their depth, and so the forest, stays bounded."""
    n = rows.count()
    times = min(trees, max(1, -(-trees * subsample // max(1, n))))
    step = F.when(F.lit(trees % 2 == 0), 2 * F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(trees // 2)) + 1).otherwise(1)
    picks = F.transform(F.sequence(F.lit(0), F.lit(times - 1)), lambda i: F.pmod(F.pmod(F.xxhash64("doc_id", F.lit(0)), F.lit(trees)) + i * step, F.lit(trees)))
    limit = math.ceil(math.log2(max(2, subsample))) + 4

    def grow(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        x = part[list(FEATURES)].to_numpy(np.float64)
        x = x[np.lexsort(x.T)]
        f = fit_forest(x, 1, len(x), 42 + int(key[0]), limit)
        return pd.DataFrame([{"tree": int(key[0]), **{k: f[k].tolist() for k in ("feature", "cut", "left", "right", "root")}}])

    schema = "tree long, feature array<long>, cut array<double>, left array<long>, right array<long>, root array<long>"
    grown = rows.select(F.explode(picks).alias("tree"), *FEATURES).groupBy("tree").applyInPandas(grow, schema).collect()
    out: dict[str, list] = {"feature": [], "cut": [], "left": [], "right": [], "root": []}
    for t in sorted(grown, key=lambda t: t["tree"]):
        base = len(out["cut"])
        out["feature"] += t["feature"]
        out["cut"] += t["cut"]
        for k in ("left", "right", "root"):
            out[k] += [base + i for i in t[k]]
    forest = {k: np.array(v, np.float64 if k == "cut" else np.int64) for k, v in out.items()}
    return forest | {"norm": np.array(float(_average_path(float(max(2, n * times // trees)))))}


def threshold(scored: DataFrame, good_loss: float = GOOD_LOSS) -> float:
    """``calibrate`` over all rows (good, anomaly); the driver holds the share ``good_loss`` of the scores, and no rows."""
    n = {r["good"]: r["count"] for r in scored.groupBy("good").count().collect()}
    if not n.get(True) or not n.get(False):
        return float("inf")
    above = n[True] - 1 - math.ceil((n[True] - 1) * (1 - good_loss))
    least = scored.where("good").select("anomaly").orderBy(F.desc("anomaly")).offset(above).limit(1).first()[0]
    top = scored.where(~F.col("good") & (F.col("anomaly") > least)).agg(F.min("anomaly")).first()[0]
    return float((least + top) / 2) if top is not None else float(least)


def fit(stats: DataFrame, labels: DataFrame) -> tuple[dict[str, np.ndarray], float]:
    """Forest and threshold from all labelled rows: the forest from a half of them by a hash of their ids, the threshold from the other."""
    marked = labels.select("doc_id", "quality").where("quality in (0, 1)").join(stats, "doc_id")
    marked = common.written(marked.select("doc_id", (F.col("quality") == 1).alias("good"), (F.pmod(F.xxhash64("doc_id", F.lit(2)), F.lit(2)) == 0).alias("half"), *FEATURES), "labelled")
    forest = grow_forest(marked.where("good and half").select("doc_id", *FEATURES))
    rest = marked if marked.where("good and not half").isEmpty() else marked.where("not half")
    return forest, threshold(common.written(score(rest, forest), "labelled-scores").select("good", "anomaly"))


def score(stats: DataFrame, forest: dict[str, np.ndarray]) -> DataFrame:
    """``stats`` with the column ``anomaly``; the forest is of bounded size whatever the corpus."""
    shared = stats.sparkSession.sparkContext.broadcast(forest)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = np.column_stack([b.column(c).to_numpy(zero_copy_only=False) for c in FEATURES])
                part = [anomaly(shared.value, x[i : i + 2000]) for i in range(0, len(x), 2000)]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(np.concatenate(part))], [*b.schema.names, "anomaly"])

    return stats.mapInArrow(run, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in stats.schema) + ", anomaly double")


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, the counts, base_failed, anomaly and kept of every document."""
    stats = common.written(statistics(docs), "rule-statistics")
    forest, most = fit(stats, labels)
    failed = (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > REPEAT_PERCENT * F.col("n_words"))
    return (
        score(stats, forest)
        .withColumn("base_failed", failed)
        .withColumn("kept", ~F.col("base_failed") & (F.col("anomaly") <= F.lit(most)))
        .select("doc_id", *COUNTS, "base_failed", "kept", F.col("anomaly").alias("score"))
    )


def kept_rows(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that ``judge`` keeps, with all their columns.

    The forest and the threshold are fitted on rule statistics as in ``judge``; texts are then measured
    again where they are read, so that no text is shuffled."""
    forest, most = fit(common.written(statistics(docs), "rule-statistics"), labels)
    shared = docs.sparkSession.sparkContext.broadcast(forest)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = np.array([measure(t) for t in b.column("text").to_pylist()], np.float64).reshape(b.num_rows, len(COUNTS) + len(FEATURES))
            n, repeats = rows[:, 0], rows[:, COUNTS.index("n_repeat_words")]
            good = (n >= MIN_WORDS) & (100 * repeats <= REPEAT_PERCENT * n)
            x = rows[:, len(COUNTS) :]
            for i in range(0, len(x), 2000):
                good[i : i + 2000] &= anomaly(shared.value, x[i : i + 2000]) <= most
            yield b.filter(pa.array(good))
        common.trim()

    return common.over_batches(docs, run, docs.schema)


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "labels"))
