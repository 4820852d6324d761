"""Secrets by a linear-chain conditional random field, beside exact base rules.

Tokens (runs of characters that secrets are made of) are tagged B, I or O. The score of a tag at a token is a sum over its
own shape (length, classes, entropy, prefix), the two words before it, the one after it, and features of the whole text;
tag pairs have transition scores. Weights are fitted here, by gradient ascent on the log-likelihood (forward-backward), on
a bounded set of sequences made from a seeded grammar of assignments, headers, connection strings and plain prose. Texts are
decoded by Viterbi. A text in which no token can gain over O even with the best transitions keeps the all-O path, which is then
optimal, so only the others are decoded step by step.

Base rules are matched as they are and always stay; the field adds spans of kind "crf" where it finds a secret that
no base span overlaps. Defined cases: null text is empty and has no spans; offsets count code points; whole texts are read.
"""

from __future__ import annotations

import functools
import math
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from wavemotif.llm.common import WORD_CACHE, documents, map_batches, strings
from wavemotif.llm.spans import Span, digest, render

BASE = ("assign", "access", "hex")
KINDS = (*BASE, "crf")
# fixed values: the base patterns, kind and least length; hex and access runs are maximal, so the length can stand in the pattern
ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEX = re.compile(r"[0-9a-f]{24,}")

TOKEN = re.compile(r"[A-Za-z0-9+/_.=~-]+|[^\sA-Za-z0-9+/_.=~-]+")
CUE = {"password": "pw", "passwd": "pw", "pwd": "pw", "pass": "pw", "secret": "sec", "token": "tok", "bearer": "tok", "basic": "tok", "apikey": "key", "api_key": "key", "key": "key", "access_key": "key", "private_key": "key", "auth": "tok", "authorization": "tok", "credential": "sec", "credentials": "sec", "client_secret": "sec", "user": "usr", "login": "usr"}
LOWER, UPPER, DIGIT, MARK = re.compile("[a-z]"), re.compile("[A-Z]"), re.compile("[0-9]"), re.compile(r"[+/=_~.-]")
STATES = 3  # O, B, I
O, B, I = range(STATES)


def base_spans(text: str) -> list[Span]:
    spans = [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if m.end(1) - m.start(1) >= 6] if ASSIGN_HINT.search(text) else []
    spans += [("access", m.start(), m.end()) for m in ACCESS.finditer(text)] if "AKIA" in text else []
    return spans + [("hex", m.start(), m.end()) for m in HEX.finditer(text)]


ASSIGN_HINT = re.compile(r"[:=]")


def shape(token: str) -> tuple[str, ...]:
    """Features of a token by itself."""
    n = len(token)
    if not (token[0].isascii() and (token[0].isalnum() or token[0] in "+/_.=~-")):
        return ("p:" + token[:1],)
    if token.isalpha():  # TOKEN makes such tokens ASCII
        kinds = "l" if token.islower() else "U" if token.isupper() else "lU"
    else:
        kinds = ("l" if LOWER.search(token) else "") + ("U" if UPPER.search(token) else "") + ("9" if DIGIT.search(token) else "") + ("+" if MARK.search(token.strip(".")) else "")
    entropy = -sum(c / n * math.log2(c / n) for c in map(token.count, set(token)))
    size = "1" if n < 4 else "4" if n < 8 else "8" if n < 14 else "14" if n < 20 else "20" if n < 32 else "32"
    feats = [f"n:{size}", f"k:{kinds}", f"nk:{size}{kinds}", f"h:{int(entropy * 2)}", f"hn:{int(entropy)}{size}"]
    switches = 0 if kinds in ("l", "U", "9") else sum((a.isdigit() != b.isdigit()) or (a.islower() != b.islower() and a.isalpha() and b.isalpha()) for a, b in zip(token[1:], token[2:], strict=False))
    feats.append(f"sw:{min(6, switches)}")
    if token[:4] in ("ghp_", "sk_l", "sk-p", "xoxb", "eyJh", "glpa", "AIza", "npm_"):
        feats.append("known")
    return (*feats, *cue(token))


def cue(token: str) -> tuple[str, ...]:
    """What a token says to its neighbours."""
    word = token.lower().strip("=:._-")
    kind = CUE.get(word)
    if kind is None and not word.isalpha() and SPLIT.search(word):
        kind = next((CUE[w] for w in reversed(SPLIT.split(word)) if w in CUE), None)
    if kind:
        return (f"c:{kind}",)
    return ("c:sep",) if token and token[0] in ":=\"'`" or token in ("=", "==") else ("c:url",) if token.startswith(":/") else ("c:w",)


SPLIT = re.compile(r"[_.=-]")


def features(tokens: list[str]) -> list[list[str]]:
    cues = [cue(t)[0] for t in tokens]
    whole = f"f:{min(3, sum(c not in ('c:w', 'c:sep') for c in cues))}"
    out = []
    for i, t in enumerate(tokens):
        p1, p2 = cues[i - 1] if i else "^", cues[i - 2] if i > 1 else "^"
        nxt = cues[i + 1] if i + 1 < len(tokens) else "$"
        s = shape(t)
        out.append([*s, f"-1{p1}", f"-2{p2}{p1}", f"+1{nxt}", f"{whole}{s[0]}", *([f"-2{p2}{p1}{s[2]}"] if len(s) > 2 else [])])
    return out


def grammar(n: int, seed: int) -> list[list[tuple[str, int]]]:
    """n labelled token sequences."""
    r = random.Random(seed)
    alpha, low = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", "abcdefghijklmnopqrstuvwxyz"

    def word() -> str:
        w = "".join(r.choice(("th", "er", "on", "an", "re", "he", "in", "ed", "nd", "ha", "que", "ción", "schaft", "ment", "eau", "ie", "los", "t", "s", "a", "ouble")) for _ in range(r.choice((1, 1, 2, 2, 3, 4, 6, 9))))
        return r.choice((w, w, w, w.capitalize(), w.upper()))

    def rand() -> str:
        kind = r.random()
        if kind < 0.25:
            return r.choice(("ghp_", "sk_live_", "sk-proj-", "xoxb-", "glpat-", "AIza", "npm_")) + "".join(r.choices(alpha, k=r.randint(18, 36)))
        if kind < 0.5:
            return "".join(r.choices(alpha + "+/", k=r.randint(20, 44))) + r.choice(("", "="))
        if kind < 0.75:
            return "".join(r.choices("0123456789abcdef", k=r.choice((16, 20, 32, 40, 64))))
        return "".join(r.choices(alpha + "_-", k=r.randint(9, 20)))

    def noise() -> str:
        return r.choice((word, word, word, lambda: str(r.randint(0, 10 ** r.randint(1, 16))), lambda: f"{r.randint(1, 255)}.{r.randint(0, 255)}.{r.randint(0, 255)}.{r.randint(0, 255)}", lambda: word() + r.choice((".", "---", "--")), lambda: f"{word()}.example.com", lambda: f"{r.randint(1990, 2030)}-{r.randint(1, 12):02d}-{r.randint(1, 28):02d}", lambda: r.choice(("password", "token", "key", "secret", "user", "login")), lambda: r.choice("|,!@#:;()"), lambda: "".join(r.choices(low, k=r.randint(20, 40)))))()

    out = []
    for _ in range(n):
        seq = [(noise(), O) for _ in range(r.randint(2, 14))]
        if r.random() < 0.6:
            name = r.choice(("password", "passwd", "pwd", "secret", "token", "api_key", "access_key", "auth", "client_secret", "AWS_SECRET_KEY", "private_key"))
            value = rand()
            how = r.random()
            if how < 0.5:
                part = [(name, O), (r.choice((":", "=", '="', ':"')), O), (value, B)]
            elif how < 0.7:
                part = [(r.choice(("Authorization", "Proxy-Authorization", "authorization")), O), (":", O), (r.choice(("Bearer", "Basic", "Token", "basic")), O), (value, B)]
            elif how < 0.85:
                part = [("postgres", O), ("://", O), (word(), O), (":", O), (value, B), ("@", O), (word(), O)]
            else:
                cut = len(value) // 2
                part = [(name, O), (":", O), (value[:cut] or "a1", B), ("*", I), (value[cut:] or "9z", I)]
            seq += part + [(noise(), O) for _ in range(r.randint(0, 8))]
        out.append(seq)
    return out


def _logsum(x: np.ndarray, axis: int) -> np.ndarray:
    m = x.max(axis=axis, keepdims=True)
    return (m + np.log(np.exp(x - m).sum(axis=axis, keepdims=True))).squeeze(axis)


@functools.lru_cache(maxsize=1)
def fit(n: int = 1500, epochs: int = 6, seed: int = 5) -> tuple[dict[str, tuple[float, ...]], np.ndarray]:
    """(feature to weights of the tags, transitions). n bounds the fitting set."""
    data = [([f for f in features([t for t, _ in s])], [y for _, y in s]) for s in grammar(n, seed)]
    index: dict[str, int] = {}
    coded = [([np.array([index.setdefault(f, len(index)) for f in fs]) for fs in x], np.array(y)) for x, y in data]
    w, trans, g2, t2 = np.zeros((len(index), STATES)), np.zeros((STATES, STATES)), np.full((len(index), STATES), 1e-6), np.full((STATES, STATES), 1e-6)
    forbid = np.zeros((STATES, STATES))
    forbid[O, I] = -30.0
    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        for i in rng.permutation(len(coded)):
            x, y = coded[i]
            e = np.array([w[f].sum(axis=0) for f in x])
            e[0, I] -= 30
            t = trans + forbid
            a, b = np.empty_like(e), np.zeros_like(e)
            a[0] = e[0]
            for k in range(1, len(e)):
                a[k] = _logsum(a[k - 1][:, None] + t, 0) + e[k]
            for k in range(len(e) - 2, -1, -1):
                b[k] = _logsum(t + (e[k + 1] + b[k + 1])[None, :], 1)
            z = _logsum(a[-1], 0)
            grad = -np.exp(a + b - z)
            grad[np.arange(len(y)), y] += 1
            gt = -np.exp(a[:-1, :, None] + t + (e[1:] + b[1:])[:, None, :] - z).sum(axis=0)
            np.add.at(gt, (y[:-1], y[1:]), 1)
            for f, g in zip(x, grad, strict=True):
                g = g - 0.002 * w[f]
                g2[f] += g * g
                w[f] += 0.3 * g / np.sqrt(g2[f] + 1e-2)
            t2 += gt * gt
            trans += 0.3 * gt / np.sqrt(t2 + 1e-2)
    return {f: tuple(map(float, w[i])) for f, i in index.items()}, trans + forbid


CUES = ("c:pw", "c:sec", "c:tok", "c:key", "c:usr", "c:sep", "c:url", "c:w", "^", "$")


class Codes(dict):
    """Token to code, remembered for the tokens seen last."""

    def __init__(self, of):
        super().__init__()
        self.of = of

    def __missing__(self, token: str) -> int:
        if len(self) > 2 * WORD_CACHE:
            self.clear()
        got = self[token] = self.of(token)
        return got


class Tagger:
    """Scores and decodes with given weights.

    A token's features depend on its shape and on the cues around it, so scores are gathered from tables by shape and
    cues, for all tokens of a text at once; a text is decoded step by step only where some token can gain.
    """

    def __init__(self, weights: dict[str, tuple[float, ...]], trans: np.ndarray):
        self.w, self.trans = weights, trans
        t = trans
        # most that leaving O, staying and coming back can add over O to O, for one token
        self.bonus = float(max(0.0, t[O, B] - t[O, O] + max(0.0, t[B, O] - t[O, O], t[I, O] - t[O, O]), t[B, I] - t[O, O] + max(0.0, t[I, O] - t[O, O]), t[I, I] - t[O, O], t[B, B] - t[O, O], t[I, B] - t[O, O]))
        k = len(CUES)
        self.left = np.array([[np.add(self.of(f"-1{p1}"), self.of(f"-2{p2}{p1}")) for p1 in CUES] for p2 in CUES]).reshape(k * k, STATES)
        self.right = np.array([self.of(f"+1{n}") for n in CUES])
        self.codes = Codes(self.code)
        self.shapes: dict[tuple[str, ...], int] = {}
        self.own: list[np.ndarray] = []
        self.table = np.empty((0, 4, k * k, STATES))

    def of(self, *feats: str) -> np.ndarray:
        return np.sum([self.w.get(f, (0.0,) * STATES) for f in feats], axis=0)

    def code(self, token: str) -> int:
        """Number of the shape times 16 and number of the cue."""
        s = shape(token)
        if s not in self.shapes:
            self.shapes[s] = len(self.shapes)
            pair = np.array([self.of(f"-2{p2}{p1}{s[2]}") if len(s) > 2 else np.zeros(STATES) for p2 in CUES for p1 in CUES])
            self.own.append(np.array([self.of(*s, f"f:{whole}{s[0]}") + pair for whole in range(4)]))
        return self.shapes[s] * 16 + CUES.index(s[-1] if s[-1] in CUES else cue(token)[0])

    def scores(self, tokens: list[str]) -> np.ndarray:
        codes = np.fromiter(map(self.codes.__getitem__, tokens), np.int64, len(tokens))
        if len(self.own) > len(self.table):
            self.table = np.concatenate([self.table, np.stack(self.own[len(self.table) :])])
        cues, shapes = codes & 15, codes >> 4
        p1 = np.concatenate([[8], cues[:-1]])
        p2 = np.concatenate([[8], p1[:-1]])
        left = p2 * len(CUES) + p1
        nxt = np.concatenate([cues[1:], [9]])
        whole = min(3, int(np.count_nonzero((cues != 5) & (cues != 7))))
        e = self.table[shapes, whole, left] + self.left[left] + self.right[nxt]
        e[0, I] -= 30
        return e

    def decode(self, e: np.ndarray) -> list[int]:
        """The best tags by Viterbi, ties to the lower tag; in plain numbers, as arrays of three cost more to make than to add."""
        (oo, ob, oi), (bo, bb, bi), (io, ib, ii) = self.trans.tolist()
        rows = iter(e.tolist())
        o, b, i = next(rows)
        back = []
        for eo, eb, ei in rows:
            to, fo = o + oo, O
            if (x := b + bo) > to:
                to, fo = x, B
            if (x := i + io) > to:
                to, fo = x, I
            tb, fb = o + ob, O
            if (x := b + bb) > tb:
                tb, fb = x, B
            if (x := i + ib) > tb:
                tb, fb = x, I
            ti, fi = o + oi, O
            if (x := b + bi) > ti:
                ti, fi = x, B
            if (x := i + ii) > ti:
                ti, fi = x, I
            o, b, i = to + eo, tb + eb, ti + ei
            back.append((fo, fb, fi))
        last = (o, b, i)
        tags = [last.index(max(last))]
        for came in reversed(back):
            tags.append(came[tags[-1]])
        return tags[::-1]

    def may_hold(self, e: np.ndarray) -> bool:
        return bool((np.maximum(e[:, B], e[:, I]) - e[:, O] + self.bonus > 0).any())

    def tags(self, tokens: list[str]) -> list[int]:
        e = self.scores(tokens)
        return self.decode(e) if self.may_hold(e) else [O] * len(tokens)

    def spans(self, text: str) -> list[tuple[int, int]]:
        tokens = TOKEN.findall(text)
        if not tokens or not self.may_hold(e := self.scores(tokens)):
            return []
        out: list[list[int]] = []
        for m, y in zip(TOKEN.finditer(text), self.decode(e), strict=True):
            if y == B:
                out.append([m.start(), m.end()])
            elif y == I and out:
                out[-1][1] = m.end()
        return [(a, b) for a, b in out]


def secrets(docs: DataFrame, fit_sequences: int = 1500) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans a row of docs."""
    weights, trans = fit(fit_sequences)
    tagger = None

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        nonlocal tagger
        tagger = tagger or Tagger(weights, trans)
        rows = []
        for text in strings(batch):
            base = base_spans(text)
            more = [("crf", a, b) for a, b in tagger.spans(text) if all(b <= x or a >= y for _, x, y in base)]
            rows.append((*[sum(s[0] == k for s in base) for k in BASE], digest(render(base, KINDS)), render(base + more, KINDS)))
        cols = list(zip(*rows, strict=True)) or [()] * 5
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(c, pa.int64()) for c in cols[:3]], *[pa.array(c, pa.string()) for c in cols[3:]]], ["doc_id", *[f"n_{k}" for k in BASE], "base_sha256", "spans"])

    return map_batches(documents(docs), fn, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
