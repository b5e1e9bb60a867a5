"""Personal data: checked base patterns, then contextual patterns bootstrapped from what these find.

Base spans are e-mail addresses, IP addresses, card numbers and telephone numbers. They are the seeds: each is
one known instance, its two words to the left and its shape are its lexical pattern. Tokens are told by blanks;
any token beside the base spans, with digits or without, is an instance of its pattern too. Scores go back and forth over the graph of patterns and
instances, all in DataFrame operations: a pattern scores the mean of its instances, less where it has few;
an instance scores as likely as that not all its patterns are wrong. Patterns above ``LEAST`` that have
``SEEDS`` known instances or more find further tokens, of kind ``other``.

Only patterns with ``SEEDS`` known instances or more can be trusted or lend trust, so base spans are counted
first, and of the other tokens only those of such patterns leave their row: (pattern, instance) pairs are counted
before the shuffle. Positions, overlaps and masked texts come from running sums and slices in blocks of the square
root of their number, so a row of k matches takes about k^1.5 small steps. Texts are never shuffled; rows are told apart by two 64-bit hashes, so repeated rows get
equal spans. A null text is empty; a null id stays null.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

KINDS = ("email", "ip", "card", "phone", "other")
#: Patterns of the base kinds. Beginnings are held to places where a run of their characters starts, and
#: repeats are possessive where that changes no match, so the time is linear in the text.
EMAIL = r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
#: Between a blank and what is none: texts are cut here into tokens with the blanks behind them.
CUT = r"(?<=[\x09-\x0D\x20])(?=[^\x09-\x0D\x20])"
BLANKS = r"[\x09-\x0D\x20]+$"
OCTETS = r"^0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?:\.0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])){3}$"
ROUNDS, LEAST, SEEDS = 3, 0.8, 3
#: Most trusted patterns that ``masked`` hands to every task.
PATTERNS_SHARED = 10_000


def let(x: Column, f: Callable[[Column], Column]) -> Column:
    """f(x) with x worked out once."""
    return F.get(F.transform(F.array(x), f), 0)


def _root(n: Column) -> Column:
    return F.ceil(F.sqrt(n)).cast("int")


def running(values: Column, join: Callable[[Column, Column], Column]) -> Column:
    """Running sums (or maxima) of an array, block by block, so that no long array is copied for each element."""

    def scan(x: Column) -> Column:
        grow = lambda out, v: F.concat(out, F.array(join(F.element_at(out, -1), v)))
        return F.aggregate(F.slice(x, 2, F.size(x)), F.slice(x, 1, 1), grow)

    def blocks(x: Column) -> Column:
        width = _root(F.size(x))
        return F.transform(F.sequence(F.lit(1), F.size(x), width), lambda i: scan(F.slice(x, i, width)))

    def shifted(parts: Column) -> Column:
        ends = scan(F.transform(parts, lambda b: F.element_at(b, -1)))
        return let(ends, lambda e: F.flatten(F.transform(parts, lambda b, k: F.when(k == 0, b).otherwise(F.transform(b, lambda v: join(F.get(e, k - 1), v))))))

    return let(values, lambda x: F.when(F.size(x) > 0, let(blocks(x), shifted)).otherwise(x))


def slices(text: Column, ranges: Column) -> Column:
    """The parts of a text from ``start`` to ``end``, by start: cut from blocks, since finding a place takes a scan."""

    def block(part: Column) -> Column:
        first = F.get(part, 0)["start"]
        last = F.array_max(F.transform(part, lambda r: r["end"]))
        cut_ = lambda t: F.transform(part, lambda r: F.substring(t, r["start"] - first + 1, r["end"] - r["start"]))
        return let(F.substring(text, first + 1, last - first), cut_)

    def blocks(x: Column) -> Column:
        width = _root(F.size(x))
        return F.flatten(F.transform(F.sequence(F.lit(1), F.size(x), width), lambda i: let(F.slice(x, i, width), block)))

    return let(ranges, lambda x: F.when(F.size(x) > 0, blocks(x)).otherwise(F.lit([]).cast("array<string>")))


def places(text: Column, pattern: str) -> Column:
    """All matches, leftmost first: array of (start, end, match) in code points."""

    def placed(found: Column) -> Column:
        steps = F.zip_with(F.slice(F.split(text, pattern, -1), 1, F.size(found)), found, lambda p, m: F.length(p) + F.length(m))
        return F.zip_with(running(steps, lambda a, b: a + b), found, lambda end, m: F.struct((end - F.length(m)).alias("start"), end.alias("end"), m.alias("match")))

    return let(F.regexp_extract_all(text, F.lit(pattern), 0), placed)


def digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def luhn(number: Column) -> Column:
    """Whether a string of digits passes Luhn's check."""
    figures = F.transform(F.split(F.reverse(number), ""), lambda c: c.cast("int"))
    doubled = F.transform(figures, lambda d, i: F.when(i % 2 == 0, d).when(d > 4, 2 * d - 9).otherwise(2 * d))
    return F.aggregate(doubled, F.lit(0), lambda a, d: a + F.coalesce(d, F.lit(0))) % 10 == 0


def _kept(kind: str, m: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return m.rlike(OCTETS)
    n = F.length(digits(m))
    return n.between(10, 15) if kind == "phone" else F.when(n.between(14, 19), luhn(digits(m))).otherwise(F.lit(False))


#: A cheap test that every text with a match passes.
_GATES = {"email": r"@[A-Za-z0-9-]", "ip": r"[0-9]\.[0-9]+\.[0-9]", "card": r"[0-9](?:[\x20-]?[0-9]){13}", "phone": r"\+[0-9]"}
_SIGNS = {"email": "@", "phone": "+"}


SPAN = "struct<start:int,rank:int,end:int>"


def found_spans(text: Column) -> Column:
    """array of (start, rank, end, match) by start, then kind; rank is the kind's place in KINDS."""
    return F.array_sort(F.concat(*[_checked(text, rank, kind, p) for rank, (kind, p) in enumerate(zip(KINDS, (EMAIL, IP, CARD, PHONE), strict=False))]))


def base_spans(text: Column) -> Column:
    """array of (start, rank, end) by start, then kind."""
    return F.transform(found_spans(text), lambda x: F.struct(x["start"].alias("start"), x["rank"].alias("rank"), x["end"].alias("end")))


def _checked(text: Column, rank: int, kind: str, pattern: str) -> Column:
    gate = text.rlike(_GATES[kind])
    if kind in _SIGNS:
        gate = text.contains(_SIGNS[kind]) & gate
    good = F.filter(places(text, pattern), lambda x: _kept(kind, x["match"]))
    spans = F.transform(good, lambda x: F.struct(x["start"].alias("start"), F.lit(rank).alias("rank"), x["end"].alias("end"), x["match"].alias("match")))
    return F.when(gate, spans).otherwise(F.lit([]).cast("array<struct<start:int,rank:int,end:int,match:string>>"))


def pattern_of(left: Column, token: Column) -> Column:
    """The words to the left with digits as 0, and the token's shape, runs shortened."""
    words = F.regexp_replace(F.regexp_replace(F.lower(left), "[0-9]+", "0"), BLANKS, "")
    shape = F.regexp_replace(F.regexp_replace(token, "[0-9]+", "0"), r"\p{L}+", "a")
    return F.concat_ws("\t", F.regexp_replace(words, r"[\x09-\x0D\x20]+", " "), shape)


def keyed(docs: DataFrame) -> DataFrame:
    """k1, k2 (the row's hashes), doc_id, text (not null) and base (spans)."""
    text = F.coalesce("text", F.lit(""))
    rows = docs.select("doc_id", text.alias("text"), F.xxhash64("doc_id", text).alias("k1"), F.xxhash64(text, "doc_id", F.lit(1)).alias("k2"))
    return rows.withColumn("base", base_spans(F.col("text")))


def left_of(pieces: Column, i: Column) -> Column:
    """The two words before a token, where there are any."""
    one = lambda k: F.when(i >= k, F.get(pieces, i - k)).otherwise("")
    return F.concat(one(2), one(1))


def starts_of(pieces: Column) -> Column:
    """Where each piece of a text starts."""
    ends = running(F.transform(pieces, lambda p: F.length(p)), lambda a, b: a + b)
    return F.zip_with(ends, pieces, lambda e, p: e - F.length(p))


def tokens_at(starts: Column, spans: Column) -> Column:
    """For each span, by start, the number of the piece that it starts in."""
    mark = "struct<at:int,own:int,piece:int>"
    pieces = F.transform(starts, lambda at, i: F.struct(at.alias("at"), F.lit(0).alias("own"), i.alias("piece")).cast(mark))
    own = F.transform(spans, lambda b: F.struct(b["start"].alias("at"), F.lit(1).alias("own"), F.lit(-1).alias("piece")).cast(mark))

    def numbered(marks: Column) -> Column:
        last = running(F.transform(marks, lambda m: m["piece"]), F.greatest)
        both = F.zip_with(marks, last, lambda m, k: F.struct(m["own"].alias("own"), k.alias("piece")))
        return F.transform(F.filter(both, lambda x: x["own"] == 1), lambda x: x["piece"])

    return let(F.array_sort(F.concat(pieces, own)), numbered)


def _seeds(text: Column, spans: Column) -> Column:
    """array of (pattern, instance) of base spans. What is written right before a span, without a blank, is its nearest word."""

    def within(pieces: Column) -> Column:
        def one(starts: Column) -> Column:
            def seed(b: Column, i: Column) -> Column:
                glued = F.substring(F.get(pieces, i), F.lit(1), b["start"] - F.get(starts, i))
                left = F.when(glued == "", left_of(pieces, i)).otherwise(F.concat(F.when(i >= 1, F.get(pieces, i - 1)).otherwise(""), glued))
                return F.struct(pattern_of(left, b["match"]).alias("pattern"), F.xxhash64(b["match"]).alias("instance"))

            return F.zip_with(spans, tokens_at(starts, spans), seed)

        return let(starts_of(pieces), one)

    return F.when(F.size(spans) > 0, let(F.split(text, CUT, -1), within))


def known_instances(docs: DataFrame) -> DataFrame:
    """pattern and instance of every base span."""
    rows = docs.select(F.coalesce("text", F.lit("")).alias("text")).select("text", found_spans(F.col("text")).alias("found"))
    seeds = rows.select(_seeds(F.col("text"), F.col("found")).alias("seeds")).select(F.explode("seeds").alias("s"))
    return seeds.select("s.pattern", "s.instance").distinct()


def shared(wanted: DataFrame) -> tuple[list[int], bool] | None:
    """The hashes of patterns for ``matching``, and whether all their shapes have a digit or an @; None if they are too many."""
    if wanted.count() > PATTERNS_SHARED:
        return None
    rows = wanted.select(F.xxhash64("pattern"), F.substring_index("pattern", "\t", -1).rlike("[0@]")).collect()
    return [r[0] for r in rows], all(r[1] for r in rows)


def _bare(x: Column) -> Column:
    return F.regexp_replace(x, BLANKS, "")


def _token(pieces: Column, starts: Column, i: Column) -> Column:
    token, start = _bare(F.get(pieces, i)), F.get(starts, i)
    return F.struct(start.alias("start"), (start + F.length(token)).alias("end"), pattern_of(left_of(pieces, i), token).alias("pattern"), F.xxhash64(token).alias("instance"))


TOKEN = "struct<start:int,end:int,pattern:string,instance:bigint>"


def tokens_of(pieces: Column, at: Column) -> Column:
    """array of (start, end, pattern, instance) of the tokens of these numbers."""
    some = let(starts_of(pieces), lambda starts: F.transform(at, lambda i: _token(pieces, starts, i)))
    return F.when(F.size(at) > 0, some).otherwise(F.lit([]).cast(f"array<{TOKEN}>"))


def beside(tokens: Column, base: Column) -> Column:
    """The tokens that no base span overlaps, by start.

    In order of their starts, a token is held against the furthest end of the spans before it and the nearest start
    of those behind."""
    mark = "struct<start:int,own:int,end:int,pattern:string,instance:bigint>"
    far = 2**31 - 1
    own = F.transform(tokens, lambda x: F.struct(x["start"].alias("start"), F.lit(1).alias("own"), x["end"].alias("end"), x["pattern"].alias("pattern"), x["instance"].alias("instance")).cast(mark))
    spans = F.transform(base, lambda b: F.struct(b["start"].alias("start"), F.lit(0).alias("own"), b["end"].alias("end"), F.lit(None).cast("string").alias("pattern"), F.lit(None).cast("bigint").alias("instance")).cast(mark))

    def apart(marks: Column) -> Column:
        before = running(F.transform(marks, lambda m: F.when(m["own"] == 0, m["end"]).otherwise(0)), F.greatest)
        behind = F.reverse(running(F.reverse(F.transform(marks, lambda m: F.when(m["own"] == 0, m["start"]).otherwise(far))), F.least))
        held = F.zip_with(marks, F.zip_with(before, behind, lambda a, b: F.struct(a.alias("end"), b.alias("start"))), lambda m, o: F.struct(m.alias("m"), o.alias("o")))
        free = F.filter(held, lambda x: (x["m"]["own"] == 1) & (x["o"]["end"] <= x["m"]["start"]) & (x["o"]["start"] >= x["m"]["end"]))
        return F.transform(free, lambda x: F.struct(*[x["m"][c].alias(c) for c in ("start", "end", "pattern", "instance")]))

    return F.when((F.size(base) == 0) | (F.size(tokens) == 0), tokens).otherwise(let(F.array_sort(F.concat(own, spans)), apart))


def matching(pieces: Column, hashes: list[int], marked: bool) -> Column:
    """array of (start, end, pattern, instance) of the tokens that have one of the patterns.

    Where all shapes have a digit or an @, no token without either can match, and none is tried."""

    def index(x: Column, i: Column) -> Column:
        hit = F.xxhash64(pattern_of(left_of(pieces, i), _bare(x))).isin(hashes) & (_bare(x) != "")
        return F.when(x.rlike("[0-9@]"), F.when(hit, i)) if marked else F.when(hit, i)

    return let(F.filter(F.transform(pieces, index), lambda i: i.isNotNull()), lambda at: tokens_of(pieces, at))


def other_tokens(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """k1, k2, start, end, pattern and instance of the tokens beside base spans that have one of the wanted patterns.

    Where the patterns are too many to share, tokens leave their rows to be joined, and places come from the texts."""
    rows = keyed(docs).select("k1", "k2", "base", F.split("text", CUT, -1).alias("pieces"))
    few = shared(wanted)
    if few is not None:
        t = rows.withColumn("found", matching(F.col("pieces"), *few) if few[0] else F.lit([]).cast(f"array<{TOKEN}>"))
    else:
        own = F.transform("pieces", lambda x, i: F.struct(i.alias("i"), pattern_of(left_of(F.col("pieces"), i), _bare(x)).alias("pattern")))
        hit = rows.select("k1", "k2", F.explode(own).alias("t")).select("k1", "k2", "t.i", "t.pattern").join(wanted.select("pattern"), "pattern", "left_semi")
        at = hit.groupBy("k1", "k2").agg(F.collect_set("i").alias("at"))
        t = rows.join(at, ["k1", "k2"]).withColumn("found", F.filter(tokens_of(F.col("pieces"), F.array_sort("at")), lambda x: x["end"] > x["start"]))
    return t.select("k1", "k2", F.explode(beside(F.col("found"), F.col("base"))).alias("t")).select("k1", "k2", "t.*")


def patterns(known: DataFrame, others: DataFrame, rounds: int = ROUNDS, least: float = LEAST, seeds: int = SEEDS) -> DataFrame:
    """pattern and score of the patterns that are trusted, from the known instances and the other tokens."""
    t = known.withColumn("known", F.lit(True)).unionByName(others.select("pattern", "instance", F.lit(False).alias("known")))
    graph = common.materialise(t.groupBy("pattern", "instance").agg(F.max("known").alias("known")))
    certain = graph.groupBy("instance").agg(F.max(F.col("known").cast("double")).alias("score"))
    scores = common.materialise(certain)
    trusted = None
    for k in range(rounds):
        by_pattern = graph.join(scores, "instance").groupBy("pattern").agg(
            (F.sum("score") / (F.count(F.lit(1)) + 0.1)).alias("trust"), F.sum(F.col("known").cast("int")).alias("seeds"))
        trusted = common.materialise(by_pattern.withColumn("trust", F.round("trust", 9)))
        if k + 1 < rounds:
            doubt = F.sum(F.log(1 - F.when(F.col("seeds") >= seeds, F.least(F.col("trust"), F.lit(0.99))).otherwise(0.0)))
            scores = graph.join(trusted, "pattern").groupBy("instance").agg(F.greatest(F.max(F.col("known").cast("double")), F.round(1 - F.exp(doubt), 9)).alias("score"))
    return trusted.where((F.col("trust") >= least) & (F.col("seeds") >= seeds)).select("pattern", F.col("trust").alias("score"))


def learned(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The trusted patterns, and the other tokens of all patterns that have enough known instances."""
    known = common.written(known_instances(docs), "pii-known")
    wanted = common.materialise(known.groupBy("pattern").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= SEEDS).select("pattern"))
    others = common.written(other_tokens(docs, wanted), "pii-tokens")
    return common.written(patterns(known, others).select("pattern"), "pii-patterns"), others


def more_spans(others: DataFrame, trusted: DataFrame) -> DataFrame:
    """k1, k2 and extra: the further spans that trusted patterns find, for rows that have any."""
    hit = others.join(trusted.select("pattern"), "pattern", "left_semi").select("k1", "k2", F.struct("start", F.lit(len(KINDS) - 1).alias("rank"), "end").alias("span"))
    return hit.groupBy("k1", "k2").agg(F.array_sort(F.collect_set("span")).alias("extra"))


def detect(docs: DataFrame) -> DataFrame:
    """doc_id, k1, k2, base and spans (base and further ones, by start) of every row."""
    trusted, others = learned(docs)
    none = F.lit([]).cast(f"array<{SPAN}>")
    rows = keyed(docs).select("doc_id", "k1", "k2", "base").join(more_spans(others, trusted), ["k1", "k2"], "left")
    return rows.select("doc_id", "k1", "k2", "base", F.array_sort(F.concat("base", F.coalesce("extra", none))).alias("spans"))


def named(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    kinds = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["rank"]), s["start"], s["end"])), ",")


def masked(docs: DataFrame) -> DataFrame:
    """``docs`` with every span of ``text`` replaced by its kind in angle brackets, and n_chars to match.

    Of overlapping spans the first is replaced, and what a later one has beyond it is cut out too. Spans are
    found again where the texts are read, so no text is shuffled: trusted patterns are counted first, and up to
    ``PATTERNS_SHARED`` of them go to every task by their hashes. Beyond that the rows'
    further spans are joined by the rows' hashes."""
    trusted, others = learned(docs)
    text = F.coalesce("text", F.lit(""))
    base = docs.select(F.struct(*docs.columns).alias("row_"), text.alias("text_"), F.xxhash64("doc_id", text).alias("k1"), F.xxhash64(text, "doc_id", F.lit(1)).alias("k2"))
    few = shared(trusted)
    base = base.withColumn("base", base_spans(F.col("text_")))
    if few is not None and not few[0]:
        rows = base.withColumnRenamed("base", "spans")
    elif few is not None:
        rows = base.withColumn("pieces_", F.split("text_", CUT, -1))
        rows = rows.withColumn("found_", matching(F.col("pieces_"), *few))
        more = F.transform(beside(F.col("found_"), F.col("base")), lambda x: F.struct(x["start"].alias("start"), F.lit(len(KINDS) - 1).alias("rank"), x["end"].alias("end")))
        rows = rows.withColumn("spans", F.array_sort(F.concat("base", more)))
    else:
        extra = more_spans(others, trusted)
        rows = base.join(extra, ["k1", "k2"], "left").withColumn("spans", F.array_sort(F.concat("base", F.coalesce("extra", F.lit([]).cast(f"array<{SPAN}>")))))
    rows = rows.withColumn("spans", F.when(F.size("spans") > 0, F.col("spans")))
    kinds = F.array(*map(F.lit, KINDS))

    def covered(ends: Column) -> Column:
        """The text without the spans, from the furthest end of the spans up to each."""

        def one(s: Column, i: Column) -> Column:
            at = F.when(i == 0, 0).otherwise(F.get(ends, i - 1))
            return F.struct(at.alias("start"), F.greatest(at, s["start"]).alias("end"), F.when(s["start"] >= at, F.concat(F.lit("<"), F.get(kinds, s["rank"]), F.lit(">"))).otherwise("").alias("mark"))

        def joined(gaps: Column) -> Column:
            return F.array_join(F.zip_with(slices(F.col("text_"), gaps), gaps, lambda part, g: F.concat(part, g["mark"])), "")

        tail = F.substring(F.col("text_"), F.element_at(ends, -1) + 1, F.length("text_"))
        return F.concat(let(F.transform("spans", one), joined), tail)

    done = let(running(F.transform("spans", lambda s: s["end"]), F.greatest), covered)
    new = rows.withColumn("new_", F.when(F.col("spans").isNotNull(), done).otherwise(F.col("row_.text")))
    out = F.col("row_").withField("text", F.col("new_"))
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        out = out.withField("n_chars", F.when(F.col("spans").isNotNull(), F.length("new_").cast(kind)).otherwise(F.col("row_.n_chars")))
    return new.select(out.alias("row_")).select("row_.*")


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's columns, and n_other and n_spans: the method's further spans, and all spans."""
    count = lambda rank: F.size(F.filter("base", lambda s: s["rank"] == rank)).cast("long")
    other = F.size(F.filter("spans", lambda s: s["rank"] == len(KINDS) - 1)).cast("long")
    return detect(common.table(spark, sf_dir, "documents")).select(
        "doc_id", *[count(k).alias(f"n_{kind}") for k, kind in enumerate(KINDS[:4])], F.sha2(named(F.col("base")), 256).alias("base_sha256"), named(F.col("spans")).alias("spans"), other.alias("n_other"), F.size("spans").cast("long").alias("n_spans"))
