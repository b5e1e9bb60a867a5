import hashlib
import re

from saferoute.llm import pii

from . import helpers as h

PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(s):
    return sum((x if i % 2 == 0 else 2 * x - 9 * (x > 4)) for i, x in enumerate(map(int, reversed(s)))) % 10 == 0


def brute(text):
    out = []
    for rank, (kind, p) in enumerate(PATTERNS.items()):
        for m in re.finditer(p, text or ""):
            d = re.sub("[^0-9]", "", m.group())
            good = {"email": True, "ip": all(int(x) <= 255 for x in m.group().split(".")) if kind == "ip" else 0, "card": 14 <= len(d) <= 19 and luhn(d or "1"), "phone": 10 <= len(d) <= 15}[kind]
            if good:
                out.append((m.start(), rank, m.end()))
    return ",".join(f"{[*PATTERNS][r]}:{a}:{b}" for a, r, b in sorted(out))


TEXTS = [
    "mail a@b.c_x@e.f and a@b.c.d@e.f.g", "1.2.3.4.5.6.7.8 and 256.1.1.1 and 001.002.003.0004 and 1.2.3", "card 4539 1488 0343 6467 or 4539-1488-0343-6467, not 4539 1488 0343 6468",
    "4539148803436467 12345678901234567890", "call +1 (017) 555-7713, +49 30 123456, +1 2", "é日本 x@y.zz 🎉 +1 (017) 555-7713 192.168.0.1", "", None, "a" * 20_000 + "@" + "b.c" * 10, "9" * 20_000, "1.1.1.1" * 50,
]


def test_base_spans_equal_brute_force(spark):
    rows = pii.detect(h.docs(spark, TEXTS)).select("doc_id", pii.named(pii.F.col("base")).alias("base")).collect()
    assert {r["doc_id"]: r["base"] for r in rows} == {i: brute(t) for i, t in enumerate(TEXTS)}


def test_contexts_find_unseen_identifiers(spark):
    texts = [f"note {i} my card number 4539 1488 0343 {6467 if i % 2 else 6467} thanks" for i in range(6)]
    known = [f"the member id {n} ok" for n in ("10.1.2.3", "10.1.2.4", "10.1.2.5", "10.9.2.6")]
    rows = {r["doc_id"]: r["spans"] for r in pii.detect(h.docs(spark, [*texts, *known, "the member id 10.1.2.999 ok", "plain 12 words"])).select("doc_id", pii.named(pii.F.col("spans")).alias("spans")).collect()}
    assert rows[len(texts) + len(known)] == "other:14:24"
    assert rows[len(texts) + len(known) + 1] == ""


def test_awkward_rows(spark):
    rows = h.table(pii.detect(h.awkward(spark)))
    assert len(rows) == 9
    assert [len(r["base"]) for r in rows if r["doc_id"] is None] == [2]
    assert pii.detect(h.empty(spark)).count() == 0


def test_masking_replaces_spans_only(spark):
    src = h.awkward(spark)
    out = pii.masked(src)
    assert out.columns == src.columns and out.count() == 9
    text = [r["text"] for r in out.collect() if r["doc_id"] is None]
    assert text == ["no id here, mail <email> or <phone> now"]
    same = {(r["doc_id"], r["text"]) for r in out.collect() if r["doc_id"] is not None}
    assert same == {(r["doc_id"], r["text"]) for r in src.collect() if r["doc_id"] is not None}


def test_empty_digest(spark):
    from saferoute.llm.queries import QUERIES

    rows = QUERIES["op2_pii"](spark, "/root/testdata/sf0.001").where("n_email + n_ip + n_card + n_phone = 0").select("base_sha256").distinct().collect()
    assert [r[0] for r in rows] == [hashlib.sha256(b"").hexdigest()]


def test_masking_is_the_same_by_patterns_and_by_join(spark, monkeypatch):
    known = [f"the member id {n} ok" for n in ("10.1.2.3", "10.1.2.4", "10.1.2.5", "10.9.2.6")]
    src = h.docs(spark, [*known, "the member id 10.1.2.999 ok", "plain 12 words"])
    out = {r["doc_id"]: r["text"] for r in pii.masked(src).collect()}
    assert out[4] == "the member id <other> ok" and out[5] == "plain 12 words" and out[0] == "the member id <ip> ok"
    monkeypatch.setattr(pii, "PATTERNS_SHARED", 0)
    assert {r["doc_id"]: r["text"] for r in pii.masked(src).collect()} == out


def test_identifiers_without_digits_are_seeds_and_found(spark):
    known = [f"please write to {n}@example.org today" for n in ("ann", "bob", "cy", "dora")]
    src = h.docs(spark, [*known, "please write to jürgen@müller.de today", "a jürgen@müller.de b"])
    rows = {r["doc_id"]: r["spans"] for r in pii.detect(src).select("doc_id", pii.named(pii.F.col("spans")).alias("spans")).collect()}
    assert rows[4] == "other:16:32" and rows[5] == "" and rows[0] == "email:16:31"
    assert {r["doc_id"]: r["text"] for r in pii.masked(src).collect()}[4] == "please write to <other> today"


def test_a_spaced_number_is_one_instance_with_the_words_before_it(spark):
    known = pii.known_instances(h.docs(spark, ["my card number 4539 1488 0343 6467 and 10.0.0.1 or 10.0.0.2"])).collect()
    assert {r["pattern"] for r in known} == {"card number\t0 0 0 0", "0 and\t0.0.0.0", "0.0.0.0 or\t0.0.0.0"}


def test_many_matches_in_one_row_take_no_square(spark):
    n = 200_000
    numbers = " ".join(f"10.0.{i % 256}.{i % 250}" for i in range(n))
    src = h.docs(spark, [numbers, "the member id 10.1.2.3 ok"])
    rows = {r["doc_id"]: r for r in pii.detect(src).select("doc_id", pii.F.size("base").alias("n"), pii.F.element_at("base", -1).alias("last")).collect()}
    assert rows[0]["n"] == n and rows[0]["last"]["end"] == len(numbers) and rows[1]["n"] == 1
    assert {r["doc_id"]: r["text"] for r in pii.masked(src).collect()}[0] == " ".join(["<ip>"] * n)


def test_running_and_slices(spark):
    rows = spark.createDataFrame([([3, 1, 4, 1, 5, 9, 2],), ([7],), ([],)], "x array<int>")
    out = rows.select(pii.running(pii.F.col("x"), lambda a, b: a + b).alias("s"), pii.running(pii.F.col("x"), pii.F.greatest).alias("m")).collect()
    assert [r["s"] for r in out] == [[3, 4, 8, 9, 14, 23, 25], [7], []] and out[0]["m"] == [3, 3, 4, 4, 5, 9, 9]


def test_tokens_that_overlap_base_spans_are_left_out(spark):
    import random

    rng = random.Random(5)
    tokens = [(a, a + rng.randint(1, 6)) for a in sorted(rng.sample(range(200), 40))]
    base = [(a, 0, a + rng.randint(1, 9)) for a in sorted(rng.sample(range(200), 25))]
    want = [t for t in tokens if not any(b[0] < t[1] and b[2] > t[0] for b in base)]
    df = spark.createDataFrame([([(*t, "p", 1) for t in tokens], base)], f"t array<{pii.TOKEN}>, b array<{pii.SPAN}>")
    got = df.select(pii.beside(pii.F.col("t"), pii.F.col("b")).alias("x")).first()["x"]
    assert [(g["start"], g["end"]) for g in got] == want
