"""Token counts of a given BPE tokenizer by a transducer that is compiled from its vocabulary and merges.

A symbol is a byte, and the last byte of a piece is a symbol of its own. The tokens of a prefix end in one token only: of the tokens
that the prefix ends with, the one that stands on its own and whose merges do not cross into the last token before it. Whether they
cross is read off the ranks of the merges along the two facing edges of the tokens. So a state needs to know the longest end of what was
read that is the start of some token, and for each place inside that end which token stands last there and how many tokens the text has
up to there. States that know the same are one state. A transition on a symbol leads to one state and is annotated with the change of
the number of tokens; the sum along a path is the count. States are compiled when a text first leads to them (as lazy determinisation
does) and kept in tables; no task calls the library of the tokenizer.

Before that the file's own normaliser and split are applied: composed characters, lower case, pieces of letters, single digits, other
marks and contractions. Files with other steps are refused, and so are merges that are not in order of the tokens they use.

White space leads back to the start from every state. The state map of a chunk has therefore a short form: the characters before its
first white space (they act on whatever state comes in), the sum of complete words, and the unfinished word, which names the state that
it ends in. Such maps compose associatively; a long text is cut into chunks whose maps are composed by a balanced scan, so a word
across a cut is counted once and whole. Sums over words met before are remembered.

Letters and digits are those of the installed Unicode tables; a character that is unassigned in the tables of the library and a letter in
these (U+058B) may be cut otherwise than by the library.

Defined cases: null text is empty and has 0 tokens; whole texts are counted, of any length; rows with null doc_id stay.
"""

from __future__ import annotations

import json
import unicodedata
from functools import reduce

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from wavemotif.llm.common import documents, map_batches, utf8

CHUNK = 1 << 15
#: Words and compiled transitions that a worker remembers (about 250 MB together); when full it starts anew.
WORDS = 600_000
EDGES = 400_000
SPACE = b" \t\n\r\x0b\x0c"
# fixed values: the steps of the file that are understood
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
PRE_TOKENIZER = {"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": PIECES}, "behavior": "Removed", "invert": True}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]}
#: White space as the file's expressions take it; the separators 1C to 1F are none.
WHITE = r"\t-\r\x20\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: (head, None, None): a chunk without white space. (head, count, tail): otherwise.
StateMap = tuple[bytes, int | None, bytes | None]


def byte_letters() -> list[str]:
    """The character that stands for each byte: itself if it is printable, else the next one from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(other)) for b in range(256)]


class Merges:
    """Tokens by number, the merges they are made by, and whether two may stand side by side."""

    def __init__(self, model: dict):
        if model["type"] != "BPE" or model.get("dropout") or model.get("byte_fallback") or model.get("ignore_merges") or model.get("continuing_subword_prefix"):
            raise ValueError("the tokenizer's model is not understood")
        end, vocab = model.get("end_of_word_suffix") or "", model["vocab"]
        self.number = {(t[: -len(end)], True) if end and t.endswith(end) and len(t) > len(end) else (t, False): i for t, i in vocab.items()}
        self.length = {i: len(t) for (t, _), i in self.number.items()}
        pairs = [tuple(m.split(" ", 1)) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.rank = {(vocab[a], vocab[b]): r for r, (a, b) in enumerate(pairs)}
        self.made: dict[int, tuple[int, int, int]] = {}  # token: rank, left part, right part
        for (a, b), r in self.rank.items():
            left, right = pairs[r]
            token = vocab[(left[: -len(end)] if end and left.endswith(end) else left) + right]
            if token in self.made or any(p not in self.made and self.length[p] > 1 for p in (a, b)):
                raise ValueError("merges are not in the order of the tokens they use")
            self.made[token] = (r, a, b)
        self.edges: dict[tuple[int, int], list[tuple[int, float]]] = {}
        self.beside: dict[tuple[int, int], bool] = {}
        self.alone: dict[int, bool] = {}

    def edge(self, token: int, side: int) -> list[tuple[int, float]]:
        """The token and the parts of it at its left (1) or right (2) end, each with the rank at which it is merged away."""
        got = self.edges.get((token, side))
        if got is None:
            got, part, until = [], token, float("inf")
            while True:
                got.append((part, until))
                if part not in self.made:
                    break
                until, part = self.made[part][0], self.made[part][side]
            self.edges[token, side] = got
        return got

    def crosses(self, a: int, b: int, before: float = float("inf")) -> bool:
        """Whether a merge joins the end of a with the start of b, of a rank lower than before."""
        for x, x_until in self.edge(a, 2):
            for y, y_until in self.edge(b, 1):
                r = self.rank.get((x, y))
                if r is not None and r < before and r < x_until and r <= y_until:  # of equal merges the left one comes first
                    return True
        return False

    def fits(self, a: int, b: int) -> bool:
        """Whether the two stay as they are side by side."""
        got = self.beside.get((a, b))
        if got is None:
            got = self.beside[a, b] = not self.crosses(a, b)
        return got

    def stands(self, token: int) -> bool:
        """Whether the text of a token is encoded as the token."""
        got = self.alone.get(token)
        if got is None:
            r, a, b = self.made.get(token, (None, 0, 0))
            got = self.length[token] == 1 if r is None else self.stands(a) and self.stands(b) and not self.crosses(a, b, r)
            self.alone[token] = got
        return got


class Automaton:
    """The transducer over the letters of bytes. State 0 is the start; a state is what it knows of each place inside its end."""

    def __init__(self, merges: Merges):
        self.m = merges
        self.starts = {t[:k] for t, last in merges.number for k in range(1, len(t) + (not last))}
        self.clear()

    def clear(self) -> None:
        self.edges: dict[tuple[int, str], tuple[int, int]] = {}
        self.ends: dict[tuple[int, str], int] = {}
        self.known: list[tuple[str, tuple[tuple[int | None, int], ...]]] = [("", ((None, 0),))]
        self.numbers = {self.known[0]: 0}

    def last(self, read: str, places: tuple[tuple[int | None, int], ...], ended: bool) -> tuple[int, int]:
        """The token that stands last after read, and the change of the number of tokens. places[i] is before read[i]."""
        now = places[-1][1]
        for i, (before, n) in enumerate(places):
            token = self.m.number.get((read[i:], ended))
            if token is not None and self.m.stands(token) and (before is None or self.m.fits(before, token)):
                return token, n + 1 - now
        raise ValueError(f"no token ends {read!r}")

    def step(self, state: int, letter: str) -> tuple[int, int]:
        """Compiles a transition: the next state and the change of the number of tokens."""
        end, places = self.known[state]
        read = end + letter
        token, change = self.last(read, places, False)
        places = (*places, (token, places[-1][1] + change))
        cut = next(i for i in range(len(read) + 1) if i == len(read) or read[i:] in self.starts)
        zero = places[-1][1]
        what = (read[cut:], tuple((t, n - zero) for t, n in places[cut:]))
        number = self.numbers.setdefault(what, len(self.known))
        if number == len(self.known):
            self.known.append(what)
        self.edges[state, letter] = number, change
        return number, change

    def stop(self, state: int, letter: str) -> int:
        """Compiles the transition on the last letter of a piece, which leads to the start."""
        end, places = self.known[state]
        change = self.ends[state, letter] = self.last(end + letter, places, True)[1]
        return change

    def count(self, piece: str) -> int:
        if len(self.edges) + len(self.ends) > EDGES:
            self.clear()
        state, n, edges = 0, 0, self.edges
        for letter in piece[:-1]:
            got = edges.get((state, letter)) or self.step(state, letter)
            state, n = got[0], n + got[1]
        got = self.ends.get((state, piece[-1]))
        return n + (self.stop(state, piece[-1]) if got is None else got)


class Transducer(dict):
    """Word to the number of its tokens, by the automaton."""

    def __init__(self, tokenizer_path: str):
        super().__init__()
        with open(tokenizer_path, encoding="utf-8") as f:
            given = json.load(f)
        if given["normalizer"] != NORMALIZER or given["pre_tokenizer"] != PRE_TOKENIZER or not given["model"].get("end_of_word_suffix"):
            raise ValueError("the tokenizer's normaliser or split is not understood")
        if any(t["single_word"] or t["lstrip"] or t["rstrip"] or t["normalized"] for t in given["added_tokens"]):
            raise ValueError("the tokenizer's added tokens are not understood")
        special = [t["content"] for t in given["added_tokens"] if t["content"]]
        if any(c.isspace() for t in special for c in t):
            raise ValueError("an added token holds white space")
        self.special = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        self.marks = [t.encode() for t in special]
        self.pieces = regex.compile(PIECES.replace(r"\s", WHITE))
        self.letters = byte_letters()
        self.table = {b: c for b, c in enumerate(self.letters)}
        self.automaton = Automaton(Merges(given["model"]))

    def plain(self, text: str) -> int:
        """Tokens of a text without added tokens."""
        if text.isascii() and text.isprintable():  # each byte stands for itself
            return sum(self.automaton.count(p) for p in self.pieces.findall(text.lower()))
        text = "".join(map(str.lower, unicodedata.normalize("NFC", text)))  # letter by letter: no rule looks at its neighbours
        return sum(self.automaton.count(p.encode().decode("latin-1").translate(self.table)) for p in self.pieces.findall(text))

    def __missing__(self, word: bytes) -> int:
        if len(self) >= WORDS:
            self.clear()
        text = word.decode("utf-8", "replace")
        if self.special and any(m in word for m in self.marks):
            found = self.special.findall(text)
            n = len(found) + sum(map(self.plain, self.special.split(text)))
        else:
            n = self.plain(text)
        self[word] = n
        return n

    def state_map(self, chunk: bytes) -> StateMap:
        words = chunk.split()
        head = b"" if not words or chunk[:1] in SPACE_SET else words[0]
        if len(words) == 1 and head == chunk or not chunk:
            return chunk, None, None
        tail = b"" if not words or chunk[-1:] in SPACE_SET else words[-1]
        inner = words[bool(head) : len(words) - bool(tail)]
        return head, int(np.fromiter(map(self.__getitem__, inner), np.int64, len(inner)).sum()), tail

    def emit(self, word: bytes) -> int:
        return self[word] if word else 0

    def compose(self, a: StateMap, b: StateMap) -> StateMap:
        """First a, then b."""
        if a[1] is None and b[1] is None:
            return a[0] + b[0], None, None
        if a[1] is None:
            return a[0] + b[0], b[1], b[2]
        if b[1] is None:
            return a[0], a[1], a[2] + b[0]
        return a[0], a[1] + self.emit(a[2] + b[0]) + b[1], b[2]

    def scan(self, maps: list[StateMap]) -> StateMap:
        """All maps in order, by halves: neighbours are composed until one is left."""
        while len(maps) > 1:
            maps = [reduce(self.compose, maps[i : i + 2]) for i in range(0, len(maps), 2)]
        return maps[0]

    def count(self, text: bytes) -> int:
        head, inner, tail = self.scan([self.state_map(text[i : i + CHUNK]) for i in range(0, len(text), CHUNK)] or [(b"", None, None)])
        return self.emit(head) + (self.emit(tail or b"") + inner if inner is not None else 0)


SPACE_SET = frozenset(SPACE[i : i + 1] for i in range(len(SPACE)))


def token_counts(docs: DataFrame, tokenizer_path: str, limit: int = 2048) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit a row of docs. The file of tokenizer_path is on every machine."""
    transducer = None

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        nonlocal transducer  # built on the executor
        transducer = transducer or Transducer(tokenizer_path)
        texts = utf8(batch)
        counts = [transducer.count(t) for t in texts]
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array(counts, pa.int64()), pa.array([n > limit for n in counts], pa.bool_())], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return map_batches(documents(docs), fn, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
