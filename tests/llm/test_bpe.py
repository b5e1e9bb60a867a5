import hashlib
import random

from tokenizers import Tokenizer

from saferoute.llm import bpe_automaton as b

from . import helpers as h


def library():
    return Tokenizer.from_file(b.default_path())


def texts():
    rng = random.Random(3)
    fixed = ["", "hello world", "<|endoftext|> a<|startoftext|>b", "aaaaaaaaaaaa aaaa", "don't WE'LL I'VE", "İstanbul ΣΑΣ ﬁ é ñ", "a\x1cb \x85 x　y", "日本語 123４５", "́abc", "🎉👍🏽", "x" * 3000, "=== --- !!?"]
    alphabet = "aaabbtheinres '-.,éßñ!?0123 "
    fixed += ["".join(rng.choice(alphabet) for _ in range(rng.randint(1, 50))) for _ in range(400)]
    return fixed + ["".join(chr(rng.choice([rng.randint(32, 0x250), rng.randint(0x370, 0x600), rng.randint(0x900, 0x3000)])) for _ in range(15)) for _ in range(300)]


def test_ids_and_decoding_equal_the_library():
    e, t = b.Encoder(b.default_path()), library()
    for x in texts():
        want = t.encode(x, add_special_tokens=False).ids
        ids = memoryview(e.encode(x)).cast("I").tolist()
        assert ids == want, x
        assert e.decode(ids) == t.decode(want, skip_special_tokens=False)


def test_gadgets_against_merging_by_rank():
    """A small merge list, also of one token with itself, on all words of five letters."""
    import itertools

    merges = [("a", "a"), ("a", "b"), ("aa", "b"), ("b", "a"), ("ab", "a"), ("aa", "aa"), ("b", "b</w>"), ("a", "b</w>"), ("aab", "ab")]
    vocab = {t: i for i, t in enumerate(["a", "b", "a</w>", "b</w>"])}
    for u, v in merges:
        vocab.setdefault(u + v, len(vocab))
    auto = b.Automaton(vocab, merges)

    def by_rank(word):
        parts = [*word[:-1], word[-1] + "</w>"]
        while True:
            pairs = [(merges.index(p), i) for i, p in enumerate(itertools.pairwise(parts)) if p in merges]
            if not pairs:
                return [vocab[p] for p in parts]
            i = min(pairs)[1]
            parts[i : i + 2] = [parts[i] + parts[i + 1]]

    for n in range(1, 8):
        for w in map("".join, itertools.product("ab", repeat=n)):
            assert auto.encode(w) == by_rank(w), w


def test_awkward_rows(spark):
    t = library()
    rows = h.table(b.encode(h.awkward(spark)))
    assert len(rows) == 9
    for r, src in zip(sorted(rows, key=str), sorted(h.table(h.awkward(spark)), key=str), strict=True):
        del src
        assert r["n_tokens"] == len(r["ids"]) and r["decoded_sha256"] == hashlib.sha256(t.decode(r["ids"], skip_special_tokens=False).encode()).hexdigest()
    assert b.encode(h.empty(spark)).count() == 0
