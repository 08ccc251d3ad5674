"""BPE encoding and decoding by a deterministic automaton over tokens, compiled from the merges.

Compilation. A state is the token read last; at first every state has an arc for every token. Each merge (x, y) of rank r
adds a gadget: it takes the arcs that begin with y from the states that end in x, for the two would have been joined. What
a token ends in at rank r is read off its right spine, what it begins with off its left spine: a part is there until the
merge that swallows it. Of two joins of one rank the left one comes first, so on the right side a part still counts at
the very rank that swallows it. If tokens are numbered so that a part comes right after the tokens it ends up in, in the
order of the merges that swallow it, the states of a gadget are one run of numbers, and so are its arcs. A state's row of
the transition table is therefore a short list of runs of arcs that are gone, and many states share a row. The automaton
accepts exactly one way to cut a word into tokens, and the same holds for each beginning of a word.

Encoding. Reading a word symbol by symbol, each place is reached by exactly one arc from one earlier place: that of the
longest token that ends there and that the table lets follow. So the states are entered from left to right without search,
and the word's tokens are read off backwards from its end. Decoding emits the arcs' labels.
The text is pre-split as the tokenizer's file says; its special tokens are taken from the raw text first.

The table is compiled once, by the driver, and broadcast: its size is that of the vocabulary, whatever the input.
Defined results: null and empty texts have no tokens. Long texts are encoded whole, in one task.
"""

from __future__ import annotations

import functools
import hashlib
import json
import re
from array import array
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from levelmine.llm.kernel import give_back

END = "</w>"
#: Words kept with their tokens, in each Python worker.
CACHED_WORDS = 400_000


def byte_symbols() -> list[str]:
    """The printable symbol of each byte in byte-level vocabularies: printable Latin-1 stands for itself."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out, spare = [""] * 256, 0x100
    for b in range(256):
        if b in plain:
            out[b] = chr(b)
        else:
            out[b], spare = chr(spare), spare + 1
    return out


class _Spines:
    """Each token's halves, the rank of its merge, and what the halves' merges do to what stands side by side."""

    def __init__(self, vocabulary: dict[str, int], merges: list[tuple[str, str]]):
        size = max(vocabulary.values()) + 1
        self.left, self.right, self.rank = [-1] * size, [-1] * size, [-1] * size
        self.join: dict[tuple[int, int], int] = {}
        for r, (x, y) in enumerate(merges):
            a, b, c = vocabulary[x], vocabulary[y], vocabulary[x + y]
            self.join.setdefault((a, b), r)
            if self.rank[c] < 0:
                self.left[c], self.right[c], self.rank[c] = a, b, r

    def joined_before(self, u: int, v: int, most: int) -> bool:
        """Whether a merge of rank below `most` joins some end of u with some beginning of v."""
        left, right, rank, join = self.left, self.right, self.rank, self.join
        x, until_x = u, most
        while x >= 0:
            y, until_y = v, most
            while y >= 0:
                r = join.get((x, y))
                if r is not None and r < until_x and (r < until_y or r == until_y < most):
                    return True
                y, until_y = left[y], rank[y]
            x, until_x = right[x], rank[x]
        return False

    def made(self, token: int) -> bool:
        """Whether the merges make this token of its own text: its halves may stand side by side till its turn."""
        return self.rank[token] < 0 or not self.joined_before(self.left[token], self.right[token], self.rank[token])


class _Arcs:
    """Numbers of the arcs: a part stands right after the tokens that begin with it, those swallowed last nearest to it."""

    def __init__(self, spines: _Spines):
        size = len(spines.rank)
        wholes: list[list[int]] = [[] for _ in range(size)]
        roots = []
        for t in sorted(range(size), key=spines.rank.__getitem__):
            (wholes[spines.left[t]] if spines.left[t] >= 0 else roots).append(t)
        self.place, self.begin, n = [0] * size, [0] * size, 0
        todo = [(t, True) for t in reversed(roots)]
        while todo:
            t, opening = todo.pop()
            if opening:
                self.begin[t] = n
                todo.append((t, False))
                todo += [(w, True) for w in reversed(wholes[t])]
            else:
                self.place[t], n = n, n + 1
        self.wholes = wholes
        self.turns = [[spines.rank[w] for w in ws] for ws in wholes]

    def run(self, part: int, rank: int) -> tuple[int, int]:
        """The arcs that still begin with the part when the merge of this rank has its turn."""
        i = bisect_left(self.turns[part], rank)
        return (self.begin[self.wholes[part][i]] if i < len(self.wholes[part]) else self.place[part]), self.place[part] + 1


def _union(runs: list[tuple[int, int]]) -> list[int]:
    """Sorted bounds of the union."""
    out: list[int] = []
    for a, b in sorted(runs):
        if out and a <= out[-1]:
            out[-1] = max(out[-1], b)
        else:
            out += [a, b]
    return out


@dataclass
class Transitions:
    """place: number of each token as an arc. row: of each token as a state. bounds[start[row]:start[row + 1]]: bounds of
    the runs of arcs that the state has lost. made: tokens that the merges can make."""

    place: array
    row: array
    start: array
    bounds: array
    made: bytearray

    def follows(self, u: int, v: int) -> bool:
        """Whether state u has arc v."""
        row = self.row[u]
        a = self.start[row]
        return not (bisect_right(self.bounds, self.place[v], a, self.start[row + 1]) - a) & 1


def transitions(vocabulary: dict[str, int], merges: list[tuple[str, str]]) -> Transitions:
    """The table after the gadgets of all merges, one after the other."""
    spines = _Spines(vocabulary, merges)
    arcs, size = _Arcs(spines), len(spines.rank)
    ranks: list[list[int]] = [[] for _ in range(size)]
    gone: list[list[tuple[int, int]]] = [[] for _ in range(size)]
    for (x, y), r in spines.join.items():  # in the order of the merges
        ranks[x].append(r)
        gone[x].append(arcs.run(y, r))
    rows: dict[tuple, int] = {}
    row, start, bounds = array("i"), array("i", [0]), array("i")
    for u in range(size):
        x, until, key = u, 1 << 62, []
        while x >= 0:  # all gadgets whose states include u: of each end, those before it is swallowed
            if n := bisect_left(ranks[x], until):
                key.append((x, n))
            x, until = spines.right[x], spines.rank[x]
        if (known := rows.get(tuple(key))) is None:
            known = rows[tuple(key)] = len(rows)
            bounds.extend(_union([run for x, n in key for run in gone[x][:n]]))
            start.append(len(bounds))
        row.append(known)
    return Transitions(array("i", arcs.place), row, start, bounds, bytearray(spines.made(t) for t in range(size)))


#: Symbols of a word's beginning whose states are kept, and how many beginnings.
HEAD, KEPT_HEADS = 5, 60_000
#: Lengths of tokens to look for where no longer one ends.
_SHORT = (3, 2, 1)


class MergeAutomaton:
    """The compiled table with the vocabulary: encodes words of byte symbols."""

    def __init__(self, vocabulary: dict[str, int], table: Transitions):
        self.table, self.labels = table, {i: t for t, i in vocabulary.items()}
        self.inner: dict[str, int] = {}
        self.final: dict[str, int] = {}
        self.heads: dict[str, tuple[list[int], list[int]]] = {}
        lengths: tuple[dict[str, set[int]], ...] = ({}, {})
        for t, i in vocabulary.items():
            if not table.made[i]:
                continue
            ends = t.endswith(END) and t != END
            body = t.removesuffix(END) if ends else t
            (self.final if ends else self.inner)[body] = i
            if len(body) > 3:
                lengths[ends].setdefault(body[-4:], set()).add(len(body))
        #: By their last four symbols: the lengths of the tokens that may end there, longest first.
        self.inner_ends, self.final_ends = ({k: (*sorted(v, reverse=True), 3, 2, 1) for k, v in x.items()} for x in lengths)

    def _enter(self, word: str, state: list[int], came: list[int], done: int, last: int, tokens: dict[str, int], ends: dict[str, tuple[int, ...]]) -> None:
        """Enters the states of the places done + 1 to last."""
        place, row, start, bounds = self.table.place, self.table.row, self.table.start, self.table.bounds
        for end in range(done + 1, last + 1):
            for length in ends.get(word[end - 4 : end], _SHORT) if end > 3 else _SHORT:
                at = end - length
                if at < 0 or (token := tokens.get(word[at:end])) is None:
                    continue
                if at:
                    r = row[state[at]]
                    a = start[r]
                    if bisect_right(bounds, place[token], a, start[r + 1]) - a & 1:
                        continue
                state[end], came[end] = token, at
                break
            else:
                raise ValueError(f"no tokens for {word!r}")

    def encode(self, word: str) -> list[int]:
        """Token ids of one pre-split word in byte symbols."""
        whole = self.final.get(word)
        if whole is not None:  # the start state's arc to the end: the only path there is
            return [whole]
        n = len(word)
        state, came = [-1] * (n + 1), [0] * (n + 1)
        done = 0
        if n > HEAD:  # the states of a beginning are the same in all words that have it
            head = word[:HEAD]
            known = self.heads.get(head)
            if known is None:
                self._enter(head, state, came, 0, HEAD, self.inner, self.inner_ends)
                if len(self.heads) >= KEPT_HEADS:
                    self.heads.clear()
                self.heads[head] = (state[: HEAD + 1], came[: HEAD + 1])
            else:
                state[: HEAD + 1], came[: HEAD + 1] = known
            done = HEAD
        self._enter(word, state, came, done, n - 1, self.inner, self.inner_ends)
        self._enter(word, state, came, n - 1, n, self.final, self.final_ends)
        out, end = [], n
        while end:
            out.append(state[end])
            end = came[end]
        return out[::-1]


#: Texts of these characters need no table look-up to be normalised; their letters, digits and white space.
_SIMPLE = re.compile("[^\x00-įı-ſ]")
_ENDINGS = "'s|'t|'re|'ve|'m|'ll|'d"
_LETTER, _DIGIT, _BLANK = "a-zªµºÀ-ÖØ-öø-ſ", "0-9²³¹¼-¾", "\x09-\x0d \x85\xa0"
_SIMPLE_WORDS = re.compile(f"{_ENDINGS}|[{_LETTER}A-Z]+|[{_DIGIT}]|[^{_BLANK}{_LETTER}A-Z{_DIGIT}]+")


class _Cache(dict):
    def __init__(self, make):
        super().__init__()
        self.make = make

    def __missing__(self, word):
        if len(self) >= CACHED_WORDS:
            self.clear()
        out = self[word] = self.make(word)
        return out


def _file(path: str) -> dict:
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model = spec["model"]
    if model["type"] != "BPE" or model["end_of_word_suffix"] != END or spec["decoder"]:
        raise ValueError("a BPE model with word ends and no decoder is asked for")
    return spec


@functools.cache
def compiled(path: str) -> Transitions:
    model = _file(path)["model"]
    return transitions(model["vocab"], [tuple(m if isinstance(m, list) else m.split(" ")) for m in model["merges"]])


class WordTokenizer:
    """A tokenizer file with word-final symbols: normalise, pre-split, run the automaton."""

    def __init__(self, path: str, table: Transitions):
        import regex
        from tokenizers import Tokenizer

        spec = _file(path)
        self.automaton = MergeAutomaton(spec["model"]["vocab"], table)
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.specials = re.compile("|".join(map(re.escape, self.special))) if self.special else None
        self.normalise = Tokenizer.from_file(path).normalizer.normalize_str
        self.words = regex.compile(_ENDINGS + r"|[\p{L}]+|[\p{N}]|[^\p{White_Space}\p{L}\p{N}]+")
        self.symbols = {b: s for b, s in enumerate(byte_symbols())}
        self.labels = self.automaton.labels | {i: t for t, i in self.special.items()}
        self.ids_of = _Cache(self._ids)
        self.text_of = _Cache(lambda ids: self.decode(map(int, ids.split(" "))))

    def _ids(self, word: str) -> str:
        if not (word.isascii() and word.isprintable()):
            word = word.encode("utf-8", "replace").decode("latin-1").translate(self.symbols)
        return " ".join(map(str, self.automaton.encode(word)))

    def split(self, text: str) -> list[str]:
        if _SIMPLE.search(text) is None:
            return _SIMPLE_WORDS.findall(text.lower())
        return self.words.findall(self.normalise(text))

    def encode(self, text: str | None) -> str:
        """Decimal token ids, one space between two."""
        if not text:
            return ""
        if self.specials is None or "<|" not in text:
            return " ".join(map(self.ids_of.__getitem__, self.split(text)))
        out, at = [], 0
        for m in self.specials.finditer(text):
            out += [self.ids_of[w] for w in self.split(text[at : m.start()])] + [str(self.special[m[0]])]
            at = m.end()
        return " ".join(out + [self.ids_of[w] for w in self.split(text[at:])])

    def decode(self, ids: Iterator[int]) -> str:
        return " ".join([self.labels[i] for i in ids])

    def decode_text(self, ids: str) -> str:
        return self.decode(map(int, ids.split(" "))) if ids else ""


_made: dict[str, WordTokenizer] = {}


def tokenizer(path: str, table: Broadcast | None = None) -> WordTokenizer:
    """One per Python process and file; with the table that the driver has compiled, if it is given."""
    if path not in _made:
        _made[path] = WordTokenizer(path, compiled(path) if table is None else table.value)
    return _made[path]


def shared_table(spark: SparkSession, path: str) -> Broadcast:
    """The compiled table for all tasks of this session."""
    return spark.sparkContext.broadcast(compiled(path))


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def _digests(path: str, table: Broadcast):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(path, table)
        sha = hashlib.sha256
        labels = tok.labels
        by_text = _Cache(lambda i: labels[int(i)])
        for batch in batches:
            count, ids_sha, text_sha = [], [], []
            for cell in batch.column(1):
                ids = tok.encode(cell.as_py())
                each = ids.split(" ") if ids else []
                count.append(len(each))
                ids_sha.append(sha(ids.encode()).hexdigest())
                text_sha.append(sha(" ".join(map(by_text.__getitem__, each)).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(count, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
        give_back()

    return run


def encode_digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every document."""
    rows = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    kind, path = docs.schema["doc_id"].dataType.simpleString(), path or default_path()
    return rows.mapInArrow(_digests(path, shared_table(docs.sparkSession, path)), f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode_ids(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids: the token ids themselves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(where, table)
        for batch in batches:
            ids = [[int(i) for i in tok.encode(cell.as_py()).split()] for cell in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    where = path or default_path()
    table = shared_table(docs.sparkSession, where)
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, ids array<int>")


def decode_ids(rows: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, ids -> doc_id, text by the arcs' labels."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokenizer(where, table)
        for batch in batches:
            texts = [tok.decode(cell.as_py() or []) for cell in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    where = path or default_path()
    table = shared_table(rows.sparkSession, where)
    kind = rows.schema["doc_id"].dataType.simpleString()
    return rows.select("doc_id", "ids").mapInArrow(run, f"doc_id {kind}, text string")
