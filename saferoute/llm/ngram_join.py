"""N-gram Jaccard join: a size-aware heavy-light join over sets of word shingles.

A text's set holds its distinct shingles of five words as 64-bit hashes; equal sets form one class, and
classes link where 100 * overlap >= 80 * union. The result has every document with its class's size and the
smallest doc_id of its connected component.

1. ``signed``: one pass gives each document its class and finds shingles of ``COMMON`` of all documents or
   more: at most 1 / COMMON * mean size of them, so they are broadcast, whatever the input.
2. ``sets``: a second pass deals the other shingles out to parts, as sorted numbers and places in blocks of
   rows, packed in about four octets each; each part keeps those of two places or more, with their
   number, and sends them back to their blocks by a number of their own. Of a class that lies in several blocks, the first answers. A
   set is ordered by that number, rarest first, shared by none before
   all. Two linked sets share one of the first size - ceil(0.8 size) + 1 (the prefix), so a class whose
   prefix is shared by none is done: nearly all are.
3. ``keyed``: small sets enumerate the pairs (subsets of size two) of their prefix and one more; large sets
   post the single shingles of their prefix to inverted lists, and so do the small ones within 0.8 of the
   boundary, for the large. The boundary is the size at which the cost of both, summed over the sets by
   size, is least.
4. ``links``: in each list all sets are held against its hub, the set with the smallest part shared by
   none. Lists whose sets are then in one component are done, so a group of n near copies takes n
   verifications. In the others, sets of different components are held against each other, and nothing is
   left out: short lists emit those pairs; the long lists of one hub are put together, and all outside the
   largest component are compared with all of them in blocks, within tasks. Overlaps are counted on the
   shared shingles, which hold every overlap.

Loads: a part holds PART_SIZE shingles on average and at most COMMON of all classes more; lists are never
gathered, only joined on their key, with the hub found by a combined aggregate and written, so that AQE splits
a long list. Lineage is cut by written tables in the shared folder.

Identity: a class is the 64-bit hash of its sorted 64-bit shingle hashes, and within a part shingles meet by
their lower 32 bits. So results are exact but for hash collisions, which are not looked up in the texts: two
texts of d documents fall into one class with a probability below d * d / 2^65, and a pair of sets of a and b
shingles counts one too many with a probability of a * b / (parts * 2^32), which matters only right below the limit.

The documents are read twice and must be a stored table: both passes must meet the same rows in the same
order, and an error is raised where they don't.

Nulls, empty texts and texts without words have an empty set: size 0, linked with nothing, their own
component. Fewer than five words make one shingle. Repeated rows fall into one class. A null doc_id gets its
component's smallest id where there is one. Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WIDTH, PERCENT = 5, 80
#: Share of documents from which a shingle is common; shingles in a part; word hashes kept by a worker.
COMMON, PART_SIZE, WORDS_KEPT = 0.01, 1_000_000, 150_000
#: Shingles that a worker packs at a time, and most parts that it deals them out to; beyond, it takes two steps.
BLOCK_SIZE, FAN = 1_000_000, 1024
#: Lists up to SHORT sets emit their pairs across components; longer ones are compared in blocks of BLOCK sets.
SHORT, BLOCK = 4, 512
_M1, _M2, _S = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(29)
#: Bits of the map of rows that may go.
FILTER_BITS = 1 << 26
#: Bits of a block's number within its partition; numbers from here on are those of common shingles.
BLOCK_BITS, COMMON_FROM = 22, 1 << 62


class WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) >= WORDS_KEPT:
            self.clear()
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


_hashes = WordHashes()


def forget_words() -> None:
    """Empties the table of word hashes; a function of the module, as one sent to a task would bring a table of its own."""
    _hashes.clear()


def shingles(text: str | None, width: int = WIDTH) -> np.ndarray:
    """The set of a text as sorted distinct hashes."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    a = np.fromiter(map(_hashes.__getitem__, words), np.uint64, len(words))
    width = min(width, len(a))
    n = len(a) - width + 1
    h = np.full(n, np.uint64(width))
    for k in range(width):
        h = (h ^ a[k : k + n]) * _M1
        h ^= h >> _S
    h *= _M2
    h ^= h >> _S
    h.sort()
    return h[np.concatenate([[True], h[1:] != h[:-1]])] if n > 1 else h


def class_of(s: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(s.tobytes()) - 2**63


def least_overlap(n: np.ndarray | int, percent: int = PERCENT) -> np.ndarray | int:
    """The smallest overlap of a set of n with a set that it links with."""
    return -(-n * percent // 100)


class Block:
    """Consecutive rows of a partition with about BLOCK_SIZE shingles: the sets by class, and each row's class."""

    def __init__(self, number: int) -> None:
        self.number, self.sets, self.rows, self.held = number, {}, [], 0

    def add(self, text: str | None) -> None:
        s = shingles(text)
        c = class_of(s) if len(s) else None
        self.rows.append((c, len(s)))
        if c is not None and c not in self.sets:
            self.sets[c] = s
            self.held += len(s)

    def full(self) -> bool:
        return self.held >= BLOCK_SIZE or len(self.rows) >= 60_000


def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[Block, list[pa.RecordBatch]]]:
    """Blocks with the rows that they are made of. Two passes over the same stored rows make the same blocks."""
    first = TaskContext.get().partitionId() << BLOCK_BITS
    block, rows = Block(first), []
    for batch in batches:
        start = 0
        for i, text in enumerate(batch.column("text")):
            block.add(text.as_py())
            if block.full():
                yield block, [*rows, batch.slice(start, i + 1 - start)]
                start, block, rows = i + 1, Block(block.number + 1), []
        rows.append(batch.slice(start))
    yield block, rows


def signed(docs: DataFrame) -> DataFrame:
    """kind 0: doc_id, h (hash of the text), cls, n, block of every row; kind 1: packed shingles and counts common in a block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block, rows in blocks(batches):
            done = 0
            for b in rows:
                own = block.rows[done : done + b.num_rows]
                done += b.num_rows
                cls, n = pa.array([c for c, _ in own], pa.int64()), pa.array([k for _, k in own], pa.int64())
                none = pa.nulls(len(own), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array([0] * len(own), pa.int32()), b.column("doc_id"), b.column("h"), cls, n, pa.array([block.number] * len(own), pa.int64()), none, none], names)
            if block.sets:
                shingle, count = np.unique(np.concatenate(list(block.sets.values())), return_counts=True)
                often = count >= max(4, COMMON * len(block.rows))
                blobs = _blob(shingle[often], count[often].astype(np.int64))
                longs = [pa.nulls(1, pa.int64())] * 4
                yield pa.RecordBatch.from_arrays([pa.array([1], pa.int32()), pa.nulls(1, rows[0].column("doc_id").type), *longs, *blobs], names)
        forget_words()
        common.trim()

    names = ["kind", "doc_id", "h", "cls", "n", "block", "often", "counts"]
    kind = docs.schema["doc_id"].dataType.simpleString()
    own = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h"), "text")
    return common.over_batches(own, run, f"kind int, doc_id {kind}, h long, cls long, n long, block long, often binary, counts binary")


def common_shingles(sign: DataFrame, rows: int) -> np.ndarray:
    """Shingles of COMMON of all rows or more (counted where blocks found them common), sorted."""

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for s, c in zip(b.column("often"), b.column("counts"), strict=True):
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(s.as_buffer(), np.int64)), pa.array(np.frombuffer(c.as_buffer(), np.int64))], ["s", "c"])

    counts = sign.where("kind = 1").select("often", "counts").mapInArrow(unpack, "s long, c long").groupBy("s").agg(F.sum("c").alias("c"))
    found = counts.where(F.col("c") >= max(8, COMMON * rows)).select("s").toPandas()["s"].to_numpy(np.int64)
    return np.sort(found.view(np.uint64))


def runs(keys: np.ndarray) -> Iterator[tuple[int, int, int]]:
    """(key, first, last) of the runs of a sorted array."""
    if len(keys):
        cut = np.flatnonzero(keys[1:] != keys[:-1]) + 1
        for i, j in zip(np.concatenate([[0], cut]).tolist(), np.append(cut, len(keys)).tolist(), strict=True):
            yield int(keys[i]), i, j


def _squeezed(x: np.ndarray, rising: bool) -> bytes:
    """Non-negative integers by octets of equal weight: what exceeds the least, or in a rising array the one before."""
    x = x.astype(np.uint64)
    least = x[:1] if rising else x.min(keepdims=True)
    y = np.diff(x, prepend=least) if rising else x - least
    width = max(1, (int(y.max()).bit_length() + 7) // 8)
    return least.tobytes() + bytes([width, rising]) + np.ascontiguousarray(y.view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def packed(*columns: tuple[np.ndarray, bool]) -> bytes:
    """Columns of equal length, each with whether it rises, in few bytes."""
    n = len(columns[0][0])
    raw = n.to_bytes(8, "little") + b"".join(_squeezed(*c) for c in columns if n)
    return zstandard.ZstdCompressor(level=1).compress(raw)


def unpacked(data: bytes | pa.Buffer, columns: int) -> list[np.ndarray]:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    n, at, out = int(raw[:8].view(np.int64)[0]), 8, []
    if not n:
        return [np.zeros(0, np.uint64)] * columns
    for _ in range(columns):
        least, width, rising = raw[at : at + 8].copy().view(np.uint64)[0], int(raw[at + 8]), raw[at + 9]
        at += 10
        y = np.zeros((n, 8), np.uint8)
        y[:, :width] = raw[at : at + n * width].reshape(width, n).T
        y = y.reshape(-1).view(np.uint64)
        out.append((np.cumsum(y) if rising else y) + least)
        at += n * width
    return out


def packed_set(a: np.ndarray) -> bytes:
    """A sorted set of shingle numbers."""
    return packed((a, True))


def unpacked_set(data: bytes | pa.Buffer) -> np.ndarray:
    return unpacked(data, 1)[0].view(np.int64)


def _blob(*arrays: np.ndarray) -> list[pa.Array]:
    return [pa.array([np.ascontiguousarray(a).tobytes()], pa.binary()) for a in arrays]


def code_of(df: np.ndarray) -> np.ndarray:
    """A number of classes as one octet: exact up to 200, then by steps of a fifth."""
    return np.where(df <= 200, df, np.minimum(254, 200 + 4 * np.log2(np.maximum(df, 200) / 200))).astype(np.uint64)


def home_of(block: np.ndarray, parts: int) -> np.ndarray:
    """The part that a block's results go to; ``elsewhere`` has the same in SQL."""
    return ((block >> BLOCK_BITS) * 1009 + (block & (2**BLOCK_BITS - 1))) % parts


def elsewhere(sign: DataFrame, parts: int) -> DataFrame:
    """to, kind 2, data: the (block, class) of classes that an earlier block has too."""
    pairs = common.materialise(sign.where("kind = 0 and cls is not null").select("cls", "block").distinct())
    first = pairs.groupBy("cls").agg(F.min("block").alias("first"), F.count(F.lit(1)).alias("many")).where("many > 1").drop("many")
    octets = lambda c: F.unhex(F.lpad(F.hex(c), 16, "0"))
    home = F.pmod(F.shiftright("block", BLOCK_BITS) * 1009 + F.col("block").bitwiseAND(F.lit(2**BLOCK_BITS - 1)), F.lit(parts))
    return pairs.join(first, "cls").where("block > first").select((home + parts).alias("to"), F.lit(2).alias("kind"), F.concat(octets("block"), octets("cls")).alias("data"))


def sets(docs: DataFrame, often: np.ndarray, parts: int, others: DataFrame) -> DataFrame:
    """cls, n, m (shared shingles), prefix (array of long: shared ones of the prefix and one more) and
    shared (all m, as ``packed_set``), for the classes that can have links.

    An entry is a class of a block: block << 16 and its place there. Rows are (to, kind, data): kind 0 brings
    (shingle, entry) to a part, kind 1 brings (entry, number of the shingle, code of its number of classes)
    back to the block's home, kind 3 brings a home the (entry, class, size) of a block, and kind 2 the classes
    that an earlier block answers for. Homes are numbered from ``parts`` on. Beyond FAN parts or homes a row holds a range of them
    (to < 0) and is dealt a second time, so a task never writes more than FAN rows a block."""
    shared = docs.sparkSession.sparkContext.broadcast(often)
    schema, names = "to long, kind int, data binary", ["to", "kind", "data"]
    span = -(-parts // FAN)  # parts dealt together at first
    mask = np.uint64(2**32 - 1)

    def row(to: int, kind: int, data: bytes) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([to], pa.int64()), pa.array([kind], pa.int32()), pa.array([data], pa.binary())], names)

    def tokens_out(tok: np.ndarray, entry: np.ndarray, span: int) -> Iterator[pa.RecordBatch]:
        order = np.argsort(tok)
        tok, entry = tok[order], entry[order]
        for p, i, j in runs((tok >> np.uint64(32)) // np.uint64(span)):
            yield row(p if span == 1 else -1 - p, 0, packed((tok[i:j], True), (entry[i:j], False)))

    def results_out(entry: np.ndarray, number: np.ndarray, code: np.ndarray, span: int) -> Iterator[pa.RecordBatch]:
        home = home_of((entry >> np.uint64(16)).astype(np.int64), parts) // span
        order = np.lexsort((number, entry, home))
        home, entry, number, code = home[order], entry[order], number[order], code[order]
        for p, i, j in runs(home):
            yield row(parts + p if span == 1 else -1 - p, 1, packed((entry[i:j], True), (number[i:j], False), (code[i:j], False)))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        often = shared.value
        for block, _ in blocks(batches):
            if not block.sets:
                continue
            cls = np.fromiter(block.sets, np.int64, len(block.sets))
            size = np.fromiter(map(len, block.sets.values()), np.int64, len(cls))
            tok = np.concatenate(list(block.sets.values()))
            block.sets.clear()
            first = np.uint64(block.number << 16)
            entry = first + np.repeat(np.arange(len(cls), dtype=np.uint64), size)
            where = np.searchsorted(often, tok)
            heavy = often[np.minimum(where, len(often) - 1)] == tok if len(often) else np.zeros(len(tok), bool)
            home = parts + int(home_of(np.array([block.number]), parts)[0])
            yield row(home, 3, packed((first + np.arange(len(cls), dtype=np.uint64), True), (cls.view(np.uint64), False), (size, False)))
            if heavy.any():  # common shingles are numbered behind all others and go home at once
                yield row(home, 1, packed((entry[heavy], True), (where[heavy] + COMMON_FROM, False), (np.full(int(heavy.sum()), 255), False)))
            tok, entry = tok[~heavy], entry[~heavy]
            part = (tok >> np.uint64(40)) % np.uint64(parts)
            yield from tokens_out(part << np.uint64(32) | tok & mask, entry, span)
        forget_words()
        common.trim()

    def deal_again(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Ranges of parts or homes to the parts and homes themselves."""
        held: dict[int, list] = {0: [], 1: []}
        out = {0: tokens_out, 1: results_out}

        def flush(kind: int) -> Iterator[pa.RecordBatch]:
            columns = list(map(np.concatenate, zip(*held[kind], strict=True)))
            held[kind].clear()
            yield from out[kind](*columns, 1)

        for b in batches:
            for to, kind, data in zip(*(b.column(x) for x in names), strict=True):
                to, kind = to.as_py(), kind.as_py()
                if to >= 0:
                    yield row(to, kind, data.as_py())
                    continue
                held[kind].append(unpacked(data.as_buffer(), 2 + kind))
                if sum(len(x[0]) for x in held[kind]) >= BLOCK_SIZE:
                    yield from flush(kind)
        for kind in (0, 1):
            if held[kind]:
                yield from flush(kind)

    def again(rows: DataFrame) -> DataFrame:
        return rows.repartition(2 * FAN, "to").mapInArrow(deal_again, schema) if span > 1 else rows

    def count(group: pa.Table) -> pa.Table:
        """Of a part's shingles, those of two classes or more, numbered and sent home."""
        part = group.column("to")[0].as_py()
        if part >= parts or part < 0:  # what is under way to a home passes
            return group
        tok, entry = map(np.concatenate, zip(*(unpacked(x.as_buffer(), 2) for x in group.column("data")), strict=True))
        order = np.argsort(tok)
        tok, entry = tok[order], entry[order]
        same = tok[1:] == tok[:-1]
        again = np.concatenate([same, [False]]) | np.concatenate([[False], same])
        tok, entry = tok[again], entry[again]
        order = np.lexsort((entry, tok))
        tok, entry = tok[order], entry[order]
        first = np.ones(len(tok), bool)
        first[1:] = (tok[1:] != tok[:-1]) | (entry[1:] != entry[:-1])
        tok, entry = tok[first], entry[first]
        start = np.flatnonzero(np.concatenate([[True], tok[1:] != tok[:-1]])) if len(tok) else np.zeros(0, np.int64)
        df = np.diff(np.append(start, len(tok)))
        number = (part << 32) + np.repeat(np.arange(len(start)), df)
        df = np.repeat(df, df)
        keep = df > 1
        out = list(results_out(entry[keep], number[keep].astype(np.uint64), code_of(df[keep]), span))
        common.trim()
        return pa.Table.from_batches(out, row_schema)

    def gather(group: pa.Table) -> pa.Table:
        """The sets of a home's blocks: order, prefix and shared shingles."""
        by = {k: [x.as_buffer() for x, kind in zip(group.column("data"), group.column("kind"), strict=True) if kind.as_py() == k] for k in (1, 2, 3)}
        if not by[3]:
            if by[2]:
                raise RuntimeError("the two passes over the documents met different rows: give the join a stored table")
            return out_schema.empty_table()
        entries, cls, n = (np.concatenate(x) for x in zip(*(unpacked(x, 3) for x in by[3]), strict=True))
        order = np.argsort(entries)
        entries, cls, n = entries[order], cls[order].view(np.int64), n[order].astype(np.int64)
        gone = {tuple(np.frombuffer(x, ">i8").tolist()) for x in by[2]}
        at = list(zip((entries >> np.uint64(16)).tolist(), cls.tolist(), strict=True)) if gone else []
        if len(gone.intersection(at)) < len(gone):
            raise RuntimeError("the two passes over the documents met different rows: give the join a stored table")
        if not by[1]:
            return out_schema.empty_table()
        entry, number, code = (np.concatenate(x) for x in zip(*(unpacked(x, 3) for x in by[1]), strict=True))
        order = np.lexsort((number, code, entry))
        entry, number = entry[order], number[order].astype(np.int64)
        start = np.flatnonzero(np.concatenate([[True], entry[1:] != entry[:-1]]))
        stop = np.append(start[1:], len(entry))
        place = np.searchsorted(entries, entry[start])
        m = stop - start
        left = m - least_overlap(n[place]) + 1  # shared shingles within the prefix
        rows: list[list] = [[], [], [], [], []]
        for k in np.flatnonzero(left > 0):
            i = int(place[k])
            if gone and at[i] in gone:
                continue
            own = number[start[k] : stop[k]]
            for column, x in zip(rows, (int(cls[i]), int(n[i]), int(m[k]), own[: left[k] + 1].tolist(), packed_set(np.sort(own))), strict=True):
                column.append(x)
        return pa.Table.from_arrays([pa.array(x, f.type) for x, f in zip(rows, out_schema, strict=True)], schema=out_schema)

    row_schema = pa.schema([("to", pa.int64()), ("kind", pa.int32()), ("data", pa.binary())])
    out_schema = pa.schema([("cls", pa.int64()), ("n", pa.int64()), ("m", pa.int64()), ("prefix", pa.list_(pa.int64())), ("shared", pa.binary())])
    dealt = again(common.over_batches(docs.select("text"), deal, schema))
    counted = again(dealt.repartition(2 * parts, "to").groupBy("to").applyInArrow(count, schema))
    return counted.unionAll(others).repartition(parts, "to").groupBy("to").applyInArrow(gather, "cls long, n long, m long, prefix array<long>, shared binary")


def boundary(rows: DataFrame) -> int:
    """The set size up to which enumerating pairs of the prefix costs less than scanning lists.

    In rows that are written and joined: a set enumerates its pairs once; it posts its prefix and meets each
    list's hub. The sums by size are taken over all sets; the boundary is where the running
    difference is least."""
    p = F.size("prefix")
    table = rows.groupBy("n").agg(F.sum(p * (p - 1) / 2).alias("enum"), F.sum(2 * F.greatest(p - 1, F.lit(1))).alias("scan")).orderBy("n").toPandas()
    if not len(table):
        return 0
    running = np.concatenate([[0.0], np.cumsum(table["enum"].to_numpy(float) - table["scan"].to_numpy(float))])
    best = int(np.argmin(running))
    return int(table["n"][best - 1]) if best else 0


def keyed(rows: DataFrame, most: int, percent: int = PERCENT) -> DataFrame:
    """key, cls, n, alone: the lists that candidates are found in. The key's last bit is 1 for pairs, 0 for single shingles."""
    base = rows.select("cls", "n", (1 - F.col("m") / F.col("n")).alias("alone"), "prefix")
    small = base.where(F.col("n") <= most).withColumn("i", F.explode(F.sequence(F.lit(0), F.size("prefix") - 1)))
    tail = F.slice("prefix", F.col("i") + 2, F.size("prefix"))
    pairs = small.select(F.explode(F.transform(tail, lambda x: F.xxhash64(F.get("prefix", F.col("i")), x).bitwiseOR(F.lit(1)))).alias("key"), "cls", "n", "alone")
    single = F.transform(F.slice("prefix", F.lit(1), F.greatest(F.size("prefix") - 1, F.lit(1))), lambda x: F.xxhash64(x).bitwiseAND(F.lit(-2)))
    return pairs.unionAll(base.where(100 * F.col("n") >= percent * F.lit(most + 1)).select(F.explode(single).alias("key"), "cls", "n", "alone"))


def listed(keys: DataFrame, most: int) -> DataFrame:
    """key, cls, n, y, ny, length: the keys of lists of two classes or more, with the list's hub and length.

    A list of single shingles is for pairs with a large set; one without any is left to the pairs."""
    lists = keys.groupBy("key").agg(F.min(F.struct("alone", "cls", "n")).alias("hub"), F.count(F.lit(1)).alias("length"), F.max("n").alias("top"))
    lists = lists.where((F.col("length") > 1) & ((F.col("key").bitwiseAND(F.lit(1)) == 1) | (F.col("top") > most)))
    lists = common.materialise(lists.select("key", F.col("hub.cls").alias("y"), F.col("hub.n").alias("ny"), "length"))
    return keys.select("key", "cls", "n").join(lists, "key")  # apart from the aggregate, a long list can be split


def near(a: Column, b: Column, percent: int = PERCENT) -> Column:
    """Whether sets of these sizes can link."""
    return 100 * F.least(a, b) >= percent * F.greatest(a, b)


def verified(pairs: DataFrame, rows: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The pairs (x, y) of classes that link."""
    own = rows.select("cls", "n", "shared")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x, y, nx, ny = (b.column(c).to_numpy() for c in ("x", "y", "nx", "ny"))
            hit = np.zeros(len(x), bool)
            for k, (s, t) in enumerate(zip(b.column("sx"), b.column("sy"), strict=True)):
                s, t = unpacked_set(s.as_buffer()), unpacked_set(t.as_buffer())
                if len(s) > len(t):
                    s, t = t, s
                at = np.searchsorted(t, s)
                overlap = int((t[np.minimum(at, len(t) - 1)] == s).sum()) if len(t) else 0
                hit[k] = 100 * overlap >= percent * (nx[k] + ny[k] - overlap)
            yield pa.RecordBatch.from_arrays([pa.array(x[hit]), pa.array(y[hit])], ["x", "y"])

    left = pairs.join(own.select(F.col("cls").alias("x"), F.col("n").alias("nx"), F.col("shared").alias("sx")), "x")
    both = left.join(own.select(F.col("cls").alias("y"), F.col("n").alias("ny"), F.col("shared").alias("sy")), "y")
    return both.select("x", "y", "nx", "ny", "sx", "sy").mapInArrow(run, "x long, y long")


def components(edges: DataFrame) -> DataFrame:
    """cls and label (the smallest cls of its component) for every class with a link."""
    both = common.materialise(edges.unionAll(edges.select("y", "x")).toDF("a", "b").distinct())
    labels = common.materialise(both.groupBy("a").agg(F.least(F.min("b"), F.min("a")).alias("label")))
    while True:
        seen = both.join(labels.select(F.col("a").alias("b"), "label"), "b").groupBy("a").agg(F.min("label").alias("seen"))
        new = labels.join(seen, "a").select("a", F.least("label", "seen").alias("next"), "label")
        jump = new.select(F.col("a").alias("next"), F.col("next").alias("far"))
        new = common.materialise(new.join(jump, "next").select("a", F.least("next", "far").alias("new"), "label"))
        common.forget(labels)
        if new.where("new <> label").isEmpty():
            common.forget(both)
            return new.select(F.col("a").alias("cls"), F.col("new").alias("label"))
        known, labels = new, new.select("a", F.col("new").alias("label"))
        labels.written_to = known.written_to


def packed_blocks(members: DataFrame, rows: DataFrame, key: str) -> DataFrame:
    """One row per (hub, key): the block's classes, sizes, labels and sets, packed. Blocks hold about BLOCK sets."""

    def pack(group: pa.Table) -> pa.Table:
        sets_ = group.column("shared").to_pylist()
        size = np.array([len(x) for x in sets_], np.int64)  # bytes
        blobs = [np.frombuffer(b"".join(sets_), np.uint8), size, *(group.column(c).to_numpy() for c in ("cls", "n", "label"))]
        head = {"hub": pa.array([group.column("hub")[0].as_py()], pa.int64()), key: pa.array([group.column(key)[0].as_py()], pa.int64())}
        return pa.table(head | {f"{key}_{c}": _blob(x)[0] for c, x in zip(("tok", "size", "cls", "n", "label"), blobs, strict=True)})

    full = members.join(rows.select("cls", "n", "shared"), "cls").select("hub", key, "cls", "n", "label", "shared")
    return full.groupBy("hub", key).applyInArrow(pack, f"hub long, {key} long, " + ", ".join(f"{key}_{c} binary" for c in ("tok", "size", "cls", "n", "label")))


def block_links(groups: DataFrame, rows: DataFrame, percent: int = PERCENT) -> DataFrame:
    """x, y: links between classes of different labels within a group (hub, cls, label).

    The classes outside a group's largest label are held against all of the group: in one task where the group
    is one block, else block by block. A task counts the overlaps as a product of matrices and puts out one
    link for two labels."""
    by_label = groups.groupBy("hub", "label").agg(F.count(F.lit(1)).alias("m"))
    largest = by_label.groupBy("hub").agg(F.max(F.struct("m", "label")).alias("top"), F.sum("m").alias("all"))
    largest = largest.select("hub", F.col("top.label").alias("main"), F.ceil(F.col("all") / BLOCK).alias("blocks"), F.ceil((F.col("all") - F.col("top.m")) / BLOCK).alias("rest_blocks"))
    members = common.materialise(groups.join(largest, "hub"))
    whole, members = members.where("blocks = 1"), members.where("blocks > 1")
    largest = largest.where("blocks > 1")
    block = lambda n: F.pmod(F.xxhash64("cls"), F.col(n))
    left = packed_blocks(members.where("label <> main").withColumn("a", block("rest_blocks")), rows, "a")
    right = packed_blocks(members.withColumn("b", block("blocks")), rows, "b")
    counts = largest.select("hub", "blocks", "rest_blocks")
    upto = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.col(n).cast("long") - 1))
    left = left.join(counts, "hub").withColumn("b", upto("blocks")).drop("blocks", "rest_blocks")
    right = right.join(counts, "hub").where("rest_blocks > 0").withColumn("a", upto("rest_blocks")).drop("blocks", "rest_blocks")

    def links_of(overlap: np.ndarray, a: tuple, b: tuple) -> pa.RecordBatch:
        """One link for two labels, from overlaps and (cls, n, label) of both sides."""
        (ca, na, la), (cb, nb, lb) = a, b
        n = na[:, None] + nb[None, :]
        i, j = np.nonzero((100 * overlap >= percent * (n - overlap)) & (la[:, None] != lb[None, :]))
        pair = np.stack([np.minimum(la[i], lb[j]), np.maximum(la[i], lb[j])], 1)
        _, at = np.unique(pair, axis=0, return_index=True)
        return pa.RecordBatch.from_arrays([pa.array(ca[i[at]]), pa.array(cb[j[at]])], ["x", "y"])

    def compare(group: pa.Table) -> pa.Table:
        """A group that is one block: its sets outside the largest label against all."""
        sets_ = [unpacked_set(x.as_buffer()) for x in group.column("shared")]
        side = tuple(group.column(c).to_numpy() for c in ("cls", "n", "label"))
        out = np.flatnonzero(side[2] != group.column("main").to_numpy())
        size = lambda x: np.array([len(s) for s in x], np.int64)
        left = [sets_[i] for i in out]
        if not left:
            return pa.table({"x": pa.array([], pa.int64()), "y": pa.array([], pa.int64())})
        overlap = overlaps(np.concatenate(left), size(left), np.concatenate(sets_), size(sets_))
        return pa.Table.from_batches([links_of(overlap, tuple(x[out] for x in side), side)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                read = lambda c, k=k: np.frombuffer(batch.column(c)[k].as_buffer(), np.int64)
                overlap = overlaps(*(x for side in "ab" for x in unpacked(batch.column(f"{side}_tok")[k].as_buffer(), read(f"{side}_size"))))
                yield links_of(overlap, *(tuple(read(f"{side}_{c}") for c in ("cls", "n", "label")) for side in "ab"))

    def unpacked(data: pa.Buffer, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        raw, ends = memoryview(data), np.cumsum(size).tolist()
        sets_ = [unpacked_set(raw[i:j]) for i, j in zip([0, *ends[:-1]], ends, strict=True)]
        return np.concatenate(sets_), np.array([len(x) for x in sets_], np.int64)

    both = left.join(right, ["hub", "a", "b"])
    many = both.select(*[f"{s}_{c}" for s in "ab" for c in ("tok", "size", "cls", "n", "label")]).mapInArrow(run, "x long, y long")
    full = whole.select("hub", "cls", "label", "main").join(rows.select("cls", "n", "shared"), "cls")
    return many.unionAll(full.groupBy("hub").applyInArrow(compare, "x long, y long"))


def overlaps(a: np.ndarray, a_size: np.ndarray, b: np.ndarray, b_size: np.ndarray, width: int = 4096) -> np.ndarray:
    """Matrix of the overlaps of two lists of sets, each given as joined elements and sizes."""
    out = np.zeros((len(a_size), len(b_size)), np.float32)
    known = np.intersect1d(a, b)
    ra, rb = np.repeat(np.arange(len(a_size)), a_size), np.repeat(np.arange(len(b_size)), b_size)
    ca, cb = np.searchsorted(known, a), np.searchsorted(known, b)
    keep_a = (ca < len(known)) & (known[np.minimum(ca, len(known) - 1)] == a) if len(known) else np.zeros(len(a), bool)
    keep_b = (cb < len(known)) & (known[np.minimum(cb, len(known) - 1)] == b) if len(known) else np.zeros(len(b), bool)
    ra, ca, rb, cb = ra[keep_a], ca[keep_a], rb[keep_b], cb[keep_b]
    for start in range(0, len(known), width):
        x, y = np.zeros((len(a_size), width), np.float32), np.zeros((len(b_size), width), np.float32)
        at = (ca >= start) & (ca < start + width)
        x[ra[at], ca[at] - start] = 1
        at = (cb >= start) & (cb < start + width)
        y[rb[at], cb[at] - start] = 1
        out += x @ y.T
    return np.rint(out).astype(np.int64)


def links(rows: DataFrame) -> DataFrame:
    """x, y: links between classes that give all components (every pair that links is in one)."""
    most = boundary(rows)
    keys = common.materialise(listed(keyed(rows, most), most))
    pairs = common.materialise(keys.where((F.col("cls") != F.col("y")) & near(F.col("n"), F.col("ny"))).select(F.col("cls").alias("x"), "y").distinct())
    first = common.materialise(verified(pairs, rows))
    labels = components(first)
    placed = common.materialise(keys.join(labels, "cls", "left").select("key", "cls", "n", "y", "length", F.coalesce("label", "cls").alias("label")))
    mixed = placed.groupBy("key").agg(F.min("label").alias("low"), F.max("label").alias("high")).where("low <> high").select("key")
    mixed = common.materialise(mixed)
    open_ = common.materialise(placed.join(mixed, "key", "left_semi"))
    common.release(rows.sparkSession)
    short = open_.where(F.col("length") <= SHORT).select("key", "cls", "n", "label")
    a, b = short.toDF("key", "x", "nx", "lx"), short.toDF("key", "y", "ny", "ly")
    rest = a.join(b, "key").where((F.col("x") < F.col("y")) & (F.col("lx") != F.col("ly")) & near(F.col("nx"), F.col("ny"))).select("x", "y").distinct()
    tried = pairs.select(F.least("x", "y").alias("x"), F.greatest("x", "y").alias("y"))
    rest = common.materialise(rest.join(tried, ["x", "y"], "left_anti"))
    long = open_.where(F.col("length") > SHORT).select(F.col("y").alias("hub"), "cls", "label").distinct()
    return first.unionAll(verified(rest, rows)).unionAll(block_links(long, rows))


def joined(docs: DataFrame) -> DataFrame:
    """doc_id, h (hash of the text), cls, n and component (its smallest doc_id) of every row."""
    spark = docs.sparkSession
    sign = common.written(signed(docs), "signed")
    rows, total = sign.where("kind = 0").agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    parts = int(max(1, -(-total // PART_SIZE), min(spark.sparkContext.defaultParallelism * 2, -(-total // 20_000))))
    table = common.written(sets(docs, common_shingles(sign, rows), parts, elsewhere(sign, parts)), "sets")
    common.release(spark)
    own = sign.where("kind = 0").select("doc_id", "h", "cls", "n")
    found = components(links(table))
    common.release(spark)
    ids = own.where("cls is not null").groupBy("cls").agg(F.min("doc_id").alias("least"))
    marked = common.materialise(ids.join(found, "cls", "left").select("cls", F.coalesce("label", "cls").alias("label"), "least"))
    whole = common.materialise(marked.groupBy("label").agg(F.min("least").alias("component")))
    by_class = marked.join(whole, "label").select("cls", "label", "component")
    return own.join(by_class, "cls", "left")


def join(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id of every row."""
    return joined(docs).select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("cls").isNull(), F.col("doc_id")).otherwise(F.col("component")).alias("component_id"))


def parted(rows: DataFrame, keys: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(rows that have none of the keys, rows that may have one); both frames have none_, id_ and h_.

    The keys' hashes are marked in a bitmap of FILTER_BITS bits, whatever their number, which every task gets: 8 MB at
    most. The more keys there are, the more other rows share a bit with one; these are told apart by a join."""
    place = F.pmod(F.xxhash64("none_", "id_", "h_"), F.lit(FILTER_BITS))
    marks = keys.select(F.bitmap_bucket_number(place).alias("bucket_"), F.bitmap_bit_position(place).alias("bit_"))
    marks = common.written(marks.groupBy("bucket_").agg(F.bitmap_construct_agg("bit_").alias("bits_")), "marks")
    placed = rows.withColumns({"bucket_": F.bitmap_bucket_number(place), "bit_": F.bitmap_bit_position(place)}).join(F.broadcast(marks), "bucket_", "left")
    octet = F.conv(F.hex(F.substring("bits_", F.floor(F.col("bit_") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    marked = F.coalesce(F.getbit(octet, (F.col("bit_") % 8).cast("int")) == 1, F.lit(False))
    return placed.where(~marked).select(*rows.columns), placed.where(marked).select(*rows.columns)


def representatives(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` of which no other stands for: one of each component, that of the smallest doc_id (null
    last), then of the smallest hash of its text; of rows that repeat both, one. Rows without words stay.

    Only the texts of rows that may go are shuffled, to be told apart exactly."""
    found = common.written(joined(docs).where("cls is not null").select("doc_id", "h", "label"), "joined")
    best = common.materialise(found.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "h")).alias("best")))
    other = found.join(best, "label").where(~(F.col("doc_id").eqNullSafe(F.col("best.doc_id")) & (F.col("h") == F.col("best.h"))))
    names = ["none_", "id_", "h_"]
    key = [F.col("doc_id").isNull().alias("none_"), F.coalesce(F.col("doc_id"), F.lit(0).cast(docs.schema["doc_id"].dataType)).alias("id_"), "h_"]
    narrow = lambda df: df.withColumnRenamed("h", "h_").select(*key).distinct()
    gone = common.written(narrow(other), "gone")
    twice = common.written(narrow(found.groupBy("doc_id", "h").count().where("count > 1")).join(gone, names, "left_anti"), "repeated")
    common.release(docs.sparkSession)
    row = docs.select(F.struct(*docs.columns).alias("row_"), "doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h_")).select("row_", *key)
    apart, maybe = parted(row, gone)
    left = apart.unionAll(maybe.join(gone, names, "left_anti").select(*row.columns))
    if not twice.isEmpty():
        apart, maybe = parted(left, twice)
        again = maybe.join(twice, names, "left_semi").groupBy(*names).agg(F.first("row_").alias("row_"))
        left = apart.unionAll(maybe.join(twice, names, "left_anti").select(*row.columns)).select("row_").unionAll(again.select("row_"))
    return left.select("row_.*")


def op3_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return join(common.table(spark, sf_dir, "documents"))
