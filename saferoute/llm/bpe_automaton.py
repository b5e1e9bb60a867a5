"""BPE encoding and decoding through a tokenization automaton.

The automaton reads tokens: its states are the start state and one state per token (the token read
last), its arcs are labelled with tokens, and its paths spell exactly the tokenizations that byte
pair encoding gives. Merges are compiled in order, each by one gadget for its pair (u, v) -> w:

* the arc u -> v is cut, since those neighbours are always merged;
* every state with an arc for u gets an arc for w (not u itself if u = v: of three, the left two merge);
* state w gets the arcs of state v.

Written out, the arcs would be the square of the vocabulary. As a gadget touches only arcs for its
own u, v and w, the arc from s to t is decided by the gadgets of s and t alone, so the table of arcs
is filled where texts ask for it and kept; filling it gives the same table as writing it out.
A word is encoded by running through its characters along arcs that the table has: the path that spells
a prefix is unique. Words are encoded once per worker and kept in a table of bounded size. Decoding emits the labels of the arcs, joined by a blank.

Nulls and empty texts have no tokens. Repeated rows give equal rows; columns other than ``doc_id`` and
``text`` are ignored. Strings of special tokens in a text become those tokens.
"""

from __future__ import annotations

import hashlib
import json
import unicodedata
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from tokenizers import Tokenizer

from . import common

#: Words kept in each worker's table, arcs in each automaton's.
WORDS_KEPT, ARCS_KEPT = 300_000, 500_000
START = -1
#: Fixed values of the tokenizer's file format: the splitting pattern and white space.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WHITE = "\t\n\x0b\x0c\r \x85\xa0                　"


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    hidden = iter(range(256, 512))
    return [chr(b) if b in shown else chr(next(hidden)) for b in range(256)]


class Arcs(dict):
    """(state, token) -> whether the finished automaton has the arc; filled where it is asked for."""

    def __init__(self, automaton: Automaton) -> None:
        self.automaton = automaton

    def __missing__(self, pair: tuple[int, int]) -> bool:
        if len(self) >= ARCS_KEPT:
            self.clear()
        self[pair] = known = self.automaton.linked(*pair) and self.automaton.whole(pair[1])
        return known


class Automaton:
    """Tokenization automaton of a merge list; tokens and states are numbered as in ``vocab``."""

    def __init__(self, vocab: dict[str, int], merges: list[tuple[str, str]], end: str = "</w>") -> None:
        self.vocab, self.end = vocab, end
        self.labels = {i: t for t, i in vocab.items()}
        self.made: dict[int, tuple[int, int, int]] = {}  # token -> left part, right part, merge number
        self.cut: dict[tuple[int, int], int] = {}  # pair -> merge number
        self.arcs: dict[tuple[int, int], bool] = {}
        self.final = Arcs(self)
        self.alive: set[int] = set()  # tokens known to be whole
        self.reach: dict[str, int] = {}  # first two or three symbols -> symbols of the longest label that begins so
        for t in vocab:
            size = len(t) - len(end) if t.endswith(end) and len(t) > len(end) else len(t)
            head = t[: min(3, size)]
            self.reach[head] = max(size, self.reach.get(head, 1))
            if size > 1:
                self.reach[head[:2]] = max(2, self.reach.get(head[:2], 2))
        for k, (u, v) in enumerate(merges):
            pair = vocab[u], vocab[v]
            if vocab[u + v] not in self.made and pair not in self.cut:
                self.made[vocab[u + v]] = (*pair, k)
                self.cut[pair] = k

    def born_linked(self, s: int, t: int) -> bool:
        """Whether the gadgets of s and t gave state s an arc for t (a later gadget may cut it)."""
        known = self.arcs.get((s, t))
        if known is None:
            left, right = self.made.get(s), self.made.get(t)
            if left is None and right is None:
                known = True
            elif right is None or left is not None and left[2] >= right[2]:
                if s == t:
                    known = self.linked(left[1], left[0], left[2])
                else:  # s came last: it took over the arcs of its right part
                    known = self.linked(left[1], t, left[2])
            else:  # t came last: its arc stands beside that of its left part
                u, v, k = right
                known = not (u == v == s) and self.linked(s, u, k) and self.linked(u, v, k)
            if len(self.arcs) >= ARCS_KEPT:
                self.arcs.clear()
            self.arcs[s, t] = known
        return known

    def linked(self, s: int, t: int, before: float = float("inf")) -> bool:
        """Whether state s has an arc for t when the merges below ``before`` are compiled."""
        return self.cut.get((s, t), before) >= before and self.born_linked(s, t)

    def encode(self, word: str) -> list[int]:
        """Tokens of one pre-split word, given as byte symbols.

        Arcs are tried from the longest label down. The path to a prefix is unique, so a place that was
        left once without reaching the end is not entered again: the run is linear in the word."""
        n = len(word)
        vocab, end, reach, final, alive = self.vocab, self.end, self.reach, self.final, self.alive
        path: list[int] = []
        at, state, dead = [0], START, set()
        i = 0
        size = reach.get(word[:3]) or reach.get(word[:2]) or 1
        while i < n:
            if size >= n - i:
                size = n - i
                t = vocab.get(word[i:] + end)
            else:
                t = vocab.get(word[i : i + size])
            while size:
                if t is not None and i + size not in dead:
                    if not path:
                        if t in alive or self.whole(t):
                            break
                    elif final[state, t]:
                        break
                size -= 1
                t = vocab.get(word[i : i + size])
            if size:
                path.append(t)
                i += size
                at.append(i)
                state = t
                size = reach.get(word[i : i + 3]) or reach.get(word[i : i + 2]) or 1
            else:  # no arc leads on: back to the place before, for a shorter label
                dead.add(at.pop())
                path.pop()
                size, i = i - at[-1] - 1, at[-1]
                state = path[-1] if path else START
                if not size:
                    continue
        return path

    def whole(self, t: int) -> bool:
        """Whether the merges really make t: its parts stay neighbours until its own gadget."""
        if t in self.alive:
            return True
        made = self.made.get(t)
        if made is None or self.linked(*made) and self.whole(made[0]) and self.whole(made[1]):
            self.alive.add(t)
            return True
        return False

    def decode(self, ids: list[int]) -> str:
        return " ".join(map(self.labels.__getitem__, ids))


class Words(dict):
    """Pre-split word in byte symbols -> its ids as little-endian 32-bit integers, filled on demand."""

    def __init__(self, automaton: Automaton) -> None:
        self.automaton = automaton

    def __missing__(self, word: str) -> bytes:
        out = array("I", self.automaton.encode(word)).tobytes()
        if len(self) >= WORDS_KEPT:
            self.clear()
        if len(word) < 100:
            self[word] = out
        return out


class Encoder(dict):
    """White-space separated piece -> its ids as little-endian 32-bit integers, filled on demand."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.automaton = Automaton(model["vocab"], merges, model["end_of_word_suffix"] or "")
        self.automaton.labels.update({i: t for t, i in self.special.items()})
        self.words = Words(self.automaton)
        self.rules = Tokenizer.from_file(path)  # its normalizer and pre-tokenizer only
        self.symbols = dict(enumerate(byte_symbols()))
        self.split = regex.compile(PATTERN)
        self.marks = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.white = regex.compile(f"[{regex.escape(WHITE)}]+")
        self.odd = regex.compile("[\x1c-\x1f]")

    def __missing__(self, piece: str) -> bytes:
        if piece.isascii() or max(piece) < "\u0250" and unicodedata.is_normalized("NFC", piece):
            words = [w.encode().decode("latin-1").translate(self.symbols) for w in self.split.findall(piece.lower())]
        else:  # normal form, lower case and classes of letters as the file's own rules have them
            words = [w for w, _ in self.rules.pre_tokenizer.pre_tokenize_str(self.rules.normalizer.normalize_str(piece))]
        out = b"".join(map(self.words.__getitem__, words))
        if len(self) >= WORDS_KEPT:
            self.clear()
        if len(piece) < 200:
            self[piece] = out
        return out

    def plain(self, text: str) -> bytes:
        pieces = self.white.split(text) if self.odd.search(text) else text.split()
        return b"".join(map(self.__getitem__, pieces))

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if self.marks is None or "<|" not in text:
            return self.plain(text)
        return b"".join(self.special[x].to_bytes(4, "little") if x in self.special else self.plain(x) for x in self.marks.split(text))

    def decode(self, ids: memoryview | list[int]) -> str:
        return self.automaton.decode(ids)


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One per worker process and vocabulary file."""
    return Encoder(path)


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode(docs: DataFrame, path: str | None = None, with_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids (array of int, optional) and the digests of ids and decoded text.

    ``path``: the vocabulary file, present on every executor (by default that of the installed package)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(path or default_path())
        for whole in batches:
            for start in range(0, whole.num_rows, 500):  # ids of few rows at a time, packed
                b = whole.slice(start, 500)
                raws, second = [], []
                for text in b.column("text").to_pylist():
                    raws.append(raw := e.encode(text))
                    second.append(hashlib.sha256(e.decode(memoryview(raw).cast("I").tolist()).encode("utf-8")).hexdigest())
                n = np.array([len(r) // 4 for r in raws], np.int64)
                columns = [b.column("doc_id"), pa.array(n), pa.array([hashlib.sha256(r).hexdigest() for r in raws], pa.string()), pa.array(second, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    offsets = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                    columns.append(pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.frombuffer(b"".join(raws), np.int32))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(columns, names)
        common.trim()

    kind = docs.schema["doc_id"].dataType.simpleString()
    schema = f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return common.over_batches(docs.select("doc_id", "text"), run, schema, "bpe", encoder.cache_clear)


def op5_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(common.table(spark, sf_dir, "documents"), with_ids=False)
