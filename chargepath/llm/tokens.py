"""Token counts by a compiled finite-state transducer.

The merge table of a byte-pair tokenizer is compiled into a deterministic
transducer over the symbols of a word piece. Encodings of prefixes extend each
other: the last token of a prefix and the encoding before it determine the
encoding, and two tokens may stand side by side just if merging their symbols
alone gives them back. So a state need only know, for each place where a token
may still begin, how far that token has come in the trie of tokens, which token
ends there, and how many tokens fewer than now were counted there. Finitely
many such states exist; they are made on first use and kept. A transition
carries the number of tokens that its symbol adds, which may be negative; a
piece's count is the sum along its walk. The last symbol of a piece is another
symbol than the same one inside, as the tokenizer has it.

Around it lies a machine of two states over white space, outside and inside a
word, which the tokenizer drops and never merges across. A text is cut into
chunks of any size. A chunk's state map is (head, inner count, tail, parted):
head ends a word that began before, tail begins one that may go on. Maps
compose associatively, so they are folded as a parallel prefix scan folds them.

Null and empty texts count 0 tokens; very long texts are read whole, chunk by
chunk; repeated rows get equal counts; an empty table gives no rows; an output
replaces a column of its name. Special strings inside a text are one token
each, as the library's default has them. Case, normal forms and the parting of
words other than ASCII are left to the library's own normalizer.
"""

import json
import os
import re

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chargepath.llm.common import boxed, unboxed, worker_cache

#: Unicode White_Space, the class that the tokenizer's patterns call \s.
_SPACES = "\t\n\x0b\x0c\r \x85\xa0  -     　"
_PARTS = re.compile(f"[{_SPACES}]+")
_ODD = re.compile("[\x1c-\x1f]")


def byte_symbols() -> list[str]:
    """The symbol of each byte: itself if it is a visible character, else one from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    out, free = [], 256
    for b in range(256):
        out.append(chr(b if b in plain else free))
        free += b not in plain
    return out


class MergeTransducer:
    """The transducer of a merge table; ``most`` states are kept."""

    def __init__(self, merges: list[tuple[str, str]], base: list[str], most: int = 200_000) -> None:
        self.rank = {tuple(m): k for k, m in enumerate(merges)}
        self.parts = {s: (s,) for s in base}
        for a, b in merges:
            self.parts.setdefault(a + b, self.parts[a] + self.parts[b])
        # The trie of tokens that their own symbols give: (children, token) by number.
        self.children: list[dict[str, int]] = [{}]
        self.token: list[str | None] = [None]
        for token, parts in self.parts.items():
            at = 0
            for symbol in parts:
                down = self.children[at].get(symbol)
                if down is None:
                    down = self.children[at][symbol] = len(self.token)
                    self.children.append({})
                    self.token.append(None)
                at = down
            self.token[at] = token
        self.alone: dict[str, bool] = {}
        self.beside: dict[tuple[str, str], bool] = {}
        self.most = most
        self._clear()

    def _clear(self) -> None:
        self.number = {((0, "", 0),): 0}
        self.states = [((0, "", 0),)]
        self.steps: list[dict[str, tuple[int, int]]] = [{}]

    def merged(self, symbols: tuple[str, ...]) -> list[str]:
        """The tokens of a few symbols, by the merge table itself."""
        out = list(symbols)
        while len(out) > 1:
            low = min(range(len(out) - 1), key=lambda k: self.rank.get((out[k], out[k + 1]), len(self.rank)))
            if (out[low], out[low + 1]) not in self.rank:
                break
            pair = out[low], out[low + 1]
            k = 0
            while k < len(out) - 1:  # all places of the best pair, from the left
                if (out[k], out[k + 1]) == pair:
                    out[k : k + 2] = [pair[0] + pair[1]]
                k += 1
        return out

    def fits(self, before: str, token: str) -> bool:
        """Whether an encoding that ends in ``before`` may go on with ``token``."""
        if token not in self.alone:
            self.alone[token] = self.merged(self.parts[token]) == [token]
        if not self.alone[token] or not before:
            return self.alone[token]
        pair = before, token
        if pair not in self.beside:
            if len(self.beside) > 2_000_000:
                self.beside = {}
            self.beside[pair] = self.merged(self.parts[before] + self.parts[token]) == [before, token]
        return self.beside[pair]

    def step(self, state: int, symbol: str) -> tuple[int, int]:
        """(next state, tokens added) of a transition, made on first use."""
        found, alive = None, []
        for node, before, fewer in self.states[state]:
            down = self.children[node].get(symbol)
            if down is None:
                continue
            if found is None and self.token[down] is not None and self.fits(before, self.token[down]):
                found = self.token[down], fewer + 1
            if self.children[down]:
                alive.append((down, before, fewer))
        token, added = found
        key = (*sorted((n, b, f - added) for n, b, f in alive), (0, token, 0))
        to = self.number.get(key)
        if to is None:
            to = self.number[key] = len(self.states)
            self.states.append(key)
            self.steps.append({})
        self.steps[state][symbol] = to, added
        return to, added

    def count(self, symbols: list[str]) -> int:
        """The number of tokens of a piece."""
        if len(self.states) > self.most:
            self._clear()
        state = total = 0
        for symbol in symbols:
            to = self.steps[state].get(symbol)
            state, added = to if to is not None else self.step(state, symbol)
            total += added
        return total


class CountTransducer:
    """Counts of words and texts; words that come again are looked up, ``limit`` of them at most."""

    def __init__(self, name: str = "word_bpe_49k.json", limit: int = 400_000) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # one task, one core
        import public_tokenizers
        import regex
        from tokenizers import Tokenizer

        path = public_tokenizers.path(name)
        with open(path, encoding="utf-8") as f:
            kept = json.load(f)
        library, model = Tokenizer.from_file(path), kept["model"]
        self.normalizer, self.pre_tokenizer = library.normalizer, library.pre_tokenizer
        self.end, self.symbols = model["end_of_word_suffix"] or "", byte_symbols()
        base = [s + e for e in dict.fromkeys(("", self.end)) for s in self.symbols]
        self.machine = MergeTransducer([tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]], base)
        self.special = re.compile("|".join(re.escape(t["content"]) for t in kept["added_tokens"]))
        self.pieces = regex.compile(kept["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.emit: dict[str, int] = {"": 0}
        self.known: dict[str, int] = {}
        self.limit = limit

    def piece(self, text: str) -> int:
        """The count of one piece in byte symbols."""
        got = self.known.get(text)
        if got is None:
            if len(self.known) > self.limit:
                self.known = {}
            symbols = list(text)
            symbols[-1] += self.end
            got = self.known[text] = self.machine.count(symbols)
        return got

    def word(self, word: str) -> int:
        """The count of text without white space."""
        if "<|" in word and (special := self.special.findall(word)):
            return len(special) + sum(self.word(part) for part in self.special.split(word) if part)
        if word.isascii() and word.isprintable():
            return sum(map(self.piece, self.pieces.findall(word.lower())))
        return sum(self.piece(p) for p, _ in self.pre_tokenizer.pre_tokenize_str(self.normalizer.normalize_str(word)))

    def split(self, chunk: str) -> list[str]:
        """Words of a chunk; empty strings stand for white space at its ends."""
        if _ODD.search(chunk):  # str.split() parts there, the tokenizer does not
            return _PARTS.split(chunk)
        words = chunk.split()
        if not words:
            return ["", ""]
        if chunk[0].isspace():
            words.insert(0, "")
        if chunk[-1].isspace():
            words.append("")
        return words

    def total(self, words: list[str]) -> int:
        emit = self.emit
        try:
            return sum(map(emit.__getitem__, words))
        except KeyError:
            if len(emit) > self.limit:
                self.emit = emit = {"": 0}
            for w in words:
                if w not in emit:
                    emit[w] = self.word(w)
            return sum(map(emit.__getitem__, words))

    def chunk_map(self, chunk: str) -> tuple[str, int, str, bool]:
        """The state map of one chunk."""
        words = self.split(chunk)
        if len(words) == 1:
            return words[0], 0, "", False
        return words[0], self.total(words[1:-1]), words[-1], True

    def compose(self, a: tuple, b: tuple) -> tuple:
        """The map of a chunk followed by another."""
        if not a[3]:
            return a[0] + b[0], b[1], b[2], b[3]
        if not b[3]:
            return a[0], a[1], a[2] + b[0], True
        return a[0], a[1] + self.total([a[2] + b[0]]) + b[1], b[2], True

    def count(self, text: str, chunk: int = 1 << 14) -> int:
        """The count of a text: its chunks' maps, folded in pairs."""
        maps = [self.chunk_map(text[lo : lo + chunk]) for lo in range(0, len(text), chunk)]
        while len(maps) > 1:
            maps = [self.compose(*maps[k : k + 2]) if k + 1 < len(maps) else maps[k] for k in range(0, len(maps), 2)]
        if not maps:
            return 0
        head, inner, tail, parted = maps[0]
        return inner + self.total([head]) + (self.total([tail]) if parted else 0)


def count_tokens(docs: DataFrame, name: str = "word_bpe_49k.json", limit: int = 2048, chunk: int = 1 << 14) -> DataFrame:
    """docs -> docs + n_bytes, n_tokens, over_limit."""

    @F.pandas_udf("long")
    def counted(texts: pd.Series) -> pd.Series:
        cache = worker_cache()
        machine = cache.get(name) or cache.setdefault(name, CountTransducer(name))
        return texts.map(lambda t: machine.count(t, chunk) if t else 0).astype("int64")

    rows = boxed(docs, text=F.coalesce(F.col("text"), F.lit("")))
    rows = rows.select("row", "text", counted("text").alias("n"))
    return unboxed(rows, n_bytes=F.octet_length("text").cast("long"), n_tokens=F.col("n"), over_limit=F.col("n") > limit)
