"""License scan, quality rules, toxicity."""

import re

import numpy as np
import pandas as pd
import pytest

from saferoute.llm import common, licenses, quality, toxicity
from saferoute.llm.queries import QUERIES

from . import helpers as h

LOWER = {i: i + 32 for i in range(65, 91)}


def words_of(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(LOWER))


def base_of(text):
    w, places, labels = words_of(text), [], set()
    for phrase, label in licenses.BASE.items():
        p = phrase.split()
        found = [i for i in range(len(w)) if w[i : i + len(p)] == p]
        places += found
        labels |= {label} if found else set()
    return len(w), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels))


TEXTS = [
    "Licensed under the Apache License, Version 2.0.", "GNU General-Public\tLicense v3; GNU GENERAL PUBLIC LICENSE", "CC BY-NC 4.0", "Ümit license, mit license", "mit der license", "cc-by cc by",
    "SPDX-License-Identifier: GPL-3.0-only", "Permission is hereby granted, free of charge, to any person obtaining a copy", None, "", "mit license " * 3000, "KKapache license",
]


def test_license_base_places(spark):
    rows = {r["doc_id"]: (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) for r in licenses.scan(h.docs(spark, TEXTS)).collect()}
    assert rows == {i: base_of(t) for i, t in enumerate(TEXTS)}


def test_license_rules_and_suppression(spark):
    rows = {r["doc_id"]: r for r in licenses.scan(h.docs(spark, TEXTS)).collect()}
    assert rows[0]["labels"] == "apache,apache-2.0" and rows[2]["labels"] == "cc-by,cc-by-nc-4.0"
    assert [d["label"] for d in rows[2]["detections"]] == ["cc-by-nc-4.0"]  # the shorter ones within are suppressed
    assert rows[6]["labels"] == "gpl-3.0" and rows[7]["labels"] == "mit" and rows[4]["labels"] == ""
    assert rows[9]["score"] == 0 and 0 < rows[0]["score"] <= 1
    assert len(licenses.rules()) > 300


def test_every_notice_is_found(spark):
    """Each notice as a text: alternatives taken first, optional words left out."""
    import re

    def plain(p):
        p = p.replace("(?:[^ ]+ ){1,8}", "the author ")
        while "(?:" in p:
            p = re.sub(r"\(\?:([^()|]*)(?:\|[^()]*)?\)(\??)", lambda m: "" if m[2] else m[1], p, count=1)
        return re.sub(r"[^\]]\?", lambda m: "" if m[0] != " ?" else " ", re.sub(r"\[(.)[^\]]*\]", r"\1", p)).replace("[0-9]", "4").strip()

    lines = [tuple(x.strip() for x in line.split(";")) for line in licenses.NOTICES.strip().splitlines()]
    rows = {r["doc_id"]: r for r in licenses.scan(h.docs(spark, [f"x {plain(p)} y" for _, p in lines])).collect()}
    for i, (label, p) in enumerate(lines):
        assert label in rows[i]["labels"], (label, plain(p), rows[i]["labels"])


def test_license_awkward_rows(spark):
    rows = h.table(licenses.scan(h.awkward(spark)))
    assert len(rows) == 9 and all(r["labels"] == "" for r in rows)
    assert licenses.scan(h.empty(spark)).count() == 0


def brute_stats(text):
    text = text or ""
    w = [x for x in re.split(r"[\x20\x09-\x0D]+", text) if x]
    seen, dup = [], 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.append(line)
    grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    hit = {k for i, g in enumerate(grams) if grams.count(g) > 1 for k in range(i, i + 5)}
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), dup, len(hit)


def test_rule_statistics_equal_brute_force(spark):
    texts = ["a b c d e a b c d e", "x\ny\nx\n\n x\nx", "é 日本 # * $ | <>", "a " * 60, "one two three", "  ", "a b c d e f " * 4 + "z", " a b c", None, ""]
    assert [quality.measure(t)[:5] for t in texts] == [brute_stats(t) for t in texts]
    many = " ".join(f"w{i}" for i in range(9000))
    assert quality.repeated_words((many + " " + many).encode().split()) == 18000


def test_forest_isolates_outliers():
    rng = np.random.default_rng(0)
    x = rng.normal(0.5, 0.05, (2000, 4))
    forest = quality.fit_forest(x)
    far = np.tile([0.5, 0.5, 0.5, 2.0], (5, 1))
    assert quality.anomaly(forest, far).min() > np.quantile(quality.anomaly(forest, x), 0.999)
    assert (quality.anomaly(quality.fit_forest(x[:0]), far) == 0).all()


def test_quality_keeps_clean_documents(spark):
    sf = "/root/testdata/sf0.01"
    got = QUERIES["op10_quality_rules"](spark, sf).toPandas().merge(common.table(spark, sf, "labels").toPandas(), on="doc_id")
    rest = got[~got.base_failed]
    assert rest[rest.quality == 1].kept.mean() > 0.98
    assert rest[rest.quality == 0].kept.mean() < 0.4
    docs, labels = common.table(spark, sf, "documents"), common.table(spark, sf, "labels")
    assert {r[0] for r in quality.kept_rows(docs, labels).select("doc_id").collect()} == {r[0] for r in quality.judge(docs, labels).where("kept").select("doc_id").collect()}


def test_quality_awkward_rows(spark):
    labels = spark.createDataFrame([(5, 1, 0), (7, 0, None), (None, 1, 1)], "doc_id long, quality int, toxic int")
    rows = h.table(quality.judge(h.awkward(spark), labels))
    assert len(rows) == 9 and sum(r["kept"] for r in rows) >= 3
    assert quality.judge(h.empty(spark), labels.limit(0)).count() == 0
    assert quality.kept_rows(h.empty(spark), labels).count() == 0


@pytest.fixture(scope="module")
def scored(spark):
    sf = "/root/testdata/sf0.1"
    got = QUERIES["op6_toxicity"](spark, sf).toPandas()
    return got, got.merge(common.table(spark, sf, "labels").toPandas(), on="doc_id")


def test_toxicity_on_held_out_rows(scored):
    got, labelled = scored
    assert got.score.between(0, 1).all() and (got.predicted == (got.score >= 0.3)).all()
    held = labelled[labelled.held_out]
    assert held[held.toxic == 1].predicted.mean() > 0.7
    assert held[held.toxic == 0].predicted.mean() < 0.05


def test_toxicity_hold_out_and_awkward_rows(spark):
    assert [toxicity.held_out(i) for i in range(4)] == [bool(x) for x in pd.Series(range(4)).map(lambda i: __import__("zlib").crc32(str(i).encode()) % 4 == 2)]
    empty = toxicity.train([], [])
    rows = h.table(toxicity.score(h.awkward(spark), empty))
    assert len(rows) == 9 and all(r["score"] == 0 for r in rows)
    model = toxicity.train(["you idiot you moron"] * 5, ["a fine day it is"] * 20)
    rows = {r["doc_id"]: r["score"] for r in h.table(toxicity.score(h.docs(spark, ["you idiot moron idiot", "a fine day", None, ""]), model))}
    assert rows[0] > rows[1] and rows[2] == rows[3]
    assert toxicity.score(h.empty(spark), model).count() == 0


def test_quality_learns_from_all_labelled_rows(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from saferoute.llm import quality

    rng = np.random.default_rng(1)
    x = rng.uniform(size=(600, len(quality.FEATURES)))
    rows = spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(x)], "doc_id long, " + ", ".join(f"{c} double" for c in quality.FEATURES))
    few = quality.grow_forest(rows, trees=4, subsample=8)  # 150 rows to a tree, not 8
    assert abs(float(few["norm"]) - float(quality._average_path(150.0))) < 1e-9 and len(few["root"]) == 4
    scores, good = quality.anomaly(few, x), np.arange(600) % 7 != 0
    scored = spark.createDataFrame([(bool(g), float(s)) for g, s in zip(good, scores, strict=True)], "good boolean, anomaly double")
    assert abs(quality.threshold(scored, 0.05) - quality.calibrate(scores, good, 0.05)) < 1e-12
    assert quality.threshold(scored.where("good")) == quality.threshold(scored.where(~F.col("good"))) == float("inf")
