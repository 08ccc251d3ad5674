from __future__ import annotations

import hashlib
import random

import pytest

from levelmine.llm import bpe
from tests.llm.support import corpus, frame

tokenizers = pytest.importorskip("tokenizers")
pytest.importorskip("public_tokenizers")


@pytest.fixture(scope="module")
def library():
    return tokenizers.Tokenizer.from_file(bpe.default_path())


def odd_texts():
    rng = random.Random(3)
    signs = "aabbeeeeinorstthl dgu'.!*0123é漢Σσİ\x00\x1fć <|endoftext|>\n\x85\x1c\xa0ſ½ǅ"
    out = ["".join(rng.choice(signs) for _ in range(rng.randint(0, 60))) for _ in range(4000)]
    return [*out, "hello<|endoftext|>World <|startoftext|>", "ΑΣ ΑΣΑ", "a" * 2000, "ab" * 900, "é" * 40, "'S 'Re it'll", "naïve café", "한국어 텍스트", "́a", "Å"]


def test_encodes_and_decodes_as_the_library(library):
    tok = bpe.tokenizer(bpe.default_path())
    for text in odd_texts():
        ids = library.encode(text, add_special_tokens=False).ids
        assert tok.encode(text) == " ".join(map(str, ids)), text
        assert tok.decode_text(tok.encode(text)) == library.decode(ids, skip_special_tokens=False), text


def test_table_is_what_the_spines_say():
    """The compiled rows against walking both tokens' spines, pair by pair."""
    model = bpe._file(bpe.default_path())["model"]
    table = bpe.compiled(bpe.default_path())
    spines = bpe._Spines(model["vocab"], [tuple(m if isinstance(m, list) else m.split(" ")) for m in model["merges"]])
    rng, size = random.Random(9), len(spines.rank)
    pairs = [(rng.randrange(size), rng.randrange(size)) for _ in range(20_000)]
    pairs += [(rng.choice([a, c]), rng.choice([b, d])) for (a, b), (c, d) in zip(rng.sample(list(spines.join), 5000), rng.sample(list(spines.join), 5000), strict=True)]
    pairs += rng.sample(list(spines.join), 5000)
    lost = 0
    for u, v in pairs:
        gone = spines.joined_before(u, v, 1 << 62)
        lost += gone
        assert table.follows(u, v) is not gone
    assert 5000 <= lost < len(pairs)


def test_digests_of_documents(spark, library):
    rows = corpus() + [(3000 + i, t) for i, t in enumerate(odd_texts()[::40])]
    want = []
    for d, t in rows:
        ids = library.encode(t or "", add_special_tokens=False).ids
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        want.append((d, len(ids), sha(" ".join(map(str, ids))), sha(library.decode(ids, skip_special_tokens=False))))
    assert sorted(map(tuple, bpe.encode_digests(frame(spark, rows)).collect()), key=str) == sorted(want, key=str)


def test_ids_round_trip(spark):
    docs = frame(spark, [(1, "the quick brown fox"), (2, None), (3, "")])
    back = dict(map(tuple, bpe.decode_ids(bpe.encode_ids(docs)).collect()))
    assert back == {1: "the</w> quick</w> brown</w> fox</w>", 2: "", 3: ""}


def test_empty_table(spark):
    assert bpe.encode_digests(frame(spark, []).limit(0)).count() == 0


def test_automaton_on_a_small_vocabulary():
    """Against merging pair by pair, for all words over three letters."""
    from itertools import product

    merges = [("a", "b"), ("b", "c"), ("ab", "c"), ("a", "a"), ("c", "c"), ("aa", "aa"), ("bc", "a"), ("b", "b")]
    symbols = ["a", "b", "c"] + [x + bpe.END for x in "abc"]
    merges += [("b", "a" + bpe.END), ("ab", "c" + bpe.END)]
    vocabulary = {t: i for i, t in enumerate(symbols + [x + y for x, y in merges])}
    auto = bpe.MergeAutomaton(vocabulary, bpe.transitions(vocabulary, merges))
    rank = {m: i for i, m in reversed(list(enumerate(merges)))}

    def merged(word):
        parts = [*word[:-1], word[-1] + bpe.END]
        while True:
            pairs = [(rank[p], i) for i, p in enumerate(zip(parts, parts[1:], strict=False)) if p in rank]
            if not pairs:
                return [vocabulary[p] for p in parts]
            _, i = min(pairs)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]

    for n in range(1, 8):
        for word in product("abc", repeat=n):
            assert auto.encode("".join(word)) == merged("".join(word)), word
