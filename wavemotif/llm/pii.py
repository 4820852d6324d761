"""Personal data by anchor expansion.

One Aho-Corasick automaton over the text finds anchors: at-signs, plus signs, digits, URL schemes and identifier
cues. At an anchor a deterministic parser expands to both sides and validates: a local part and a dotted domain around
an at-sign, four octets or a Luhn-valid card number from the first digit of a run, a dialled number after a plus sign, the
address after a scheme and the user part in it, an identifier after a cue such as "account". An identifier is a run of groups of
capitals and digits, each group with a digit; after the cue "iban" its check digits must be right. Anchors are taken
from left to right and a parser does not start before the end of what its kind has consumed, failing matches included.

Defined cases: null text is empty and has no spans; offsets count code points; nothing is cut, whatever the length.
"""

from __future__ import annotations

import re

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from wavemotif.llm.common import documents, map_batches, strings
from wavemotif.llm.spans import Span, digest, render

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "url", "url_user", "account")
# fixed values: cues that an identifier follows
CUES = ("iban", "account", "acct", "passport", "ssn", "customer id", "tax id", "national id")
SCHEMES = ("http://", "https://", "ftp://", "ssh://")

LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DIGITS = frozenset("0123456789")
DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
USER = re.compile(r"[A-Za-z0-9._%+-]+(?::[^\s@/]*)?@[A-Za-z0-9.-]+")
URL = re.compile(r"[A-Za-z0-9._~%-]+(?::[^\s@/]*)?(?:@[A-Za-z0-9._~-]+)?(?::[0-9]+)?(?:[/?#][A-Za-z0-9._~:/?#\[\]@!$&'()*+,;=%-]*)?")
ACCOUNT = re.compile(r"(?: (?:no|number|nr))?\.? ?[:#=]? ?((?=[A-Za-z0-9]*[0-9])[A-Za-z]{0,3}[0-9][A-Z0-9]*(?:[ -](?=[A-Z]{0,4}[0-9])[A-Z0-9]+)*)(?![A-Za-z0-9])", re.A)
LOWER = {c: c + 32 for c in range(65, 91)}


def automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for kind, words in (("@", "@"), ("+", "+"), ("d", DIGITS), ("s", SCHEMES), ("c", CUES)):
        for w in words:
            a.add_word(w, (kind, len(w)))
    a.make_automaton()
    return a


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def identifier(text: str, cue: str) -> bool:
    """Whether what follows a cue is an identifier: 5 to 34 letters and digits, 4 digits at least; a bank account by its check digits."""
    plain = text.replace(" ", "").replace("-", "")
    if cue == "iban":
        plain = plain.upper()
        return 15 <= len(plain) <= 34 and plain[:2].isalpha() and plain[2:4].isdigit() and int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1
    return 5 <= len(plain) <= 34 and sum(c in DIGITS for c in plain) >= 4


def find(text: str, anchors: ahocorasick.Automaton) -> list[Span]:
    """All spans of one text."""
    spans: list[Span] = []
    done = dict.fromkeys(KINDS, 0)
    last_digit = -2
    for end, (kind, n) in anchors.iter(text.translate(LOWER)):
        at = end - n + 1
        if kind == "d":
            starts, last_digit = at != last_digit + 1, at
            for k, pattern in (("ip", IP), ("card", CARD)):
                if at >= done[k] and (starts or done[k] == at) and (m := pattern.match(text, at)):
                    done[k] = m.end()
                    if k == "ip":
                        good = all(len(p.lstrip("0")) < 4 and int(p) <= 255 for p in m[0].split("."))
                    else:
                        digits = m[0].replace(" ", "").replace("-", "")
                        good = 12 <= len(digits) <= 19 and luhn(digits)
                    if good:
                        spans.append((k, at, m.end()))
        elif kind == "@":
            first = at
            while first > done["email"] and text[first - 1] in LOCAL:
                first -= 1
            if first < at and (m := DOMAIN.match(text, at)):
                done["email"] = m.end()
                spans.append(("email", first, m.end()))
        elif kind == "+":
            if at >= done["phone"] and (m := PHONE.match(text, at)):
                done["phone"] = m.end()
                if 9 <= sum(c in DIGITS for c in m[0]) <= 15:
                    spans.append(("phone", at, m.end()))
        elif kind == "s":
            if at >= done["url"] and (m := URL.match(text, end + 1)):
                done["url"] = m.end()
                stop = at + len(text[at : m.end()].rstrip(".,;:!?'()"))
                if "." in text[end + 1 : stop]:
                    spans.append(("url", at, stop))
            if m := USER.match(text, end + 1):
                spans.append(("url_user", end + 1, m.end()))
        elif end + 1 >= done["account"] and (not at or not text[at - 1].isalnum()) and (m := ACCOUNT.match(text, end + 1)) and identifier(m[1], text[at : end + 1].translate(LOWER)):
            done["account"] = m.end()
            spans.append(("account", m.start(1), m.end()))
    return spans


def personal_data(docs: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans a row of docs."""

    anchors = None

    def fn(batch: pa.RecordBatch) -> pa.RecordBatch:
        nonlocal anchors  # built on the executor
        anchors = anchors or automaton()
        rows = []
        for text in strings(batch):
            found = find(text, anchors)
            base = [s for s in found if s[0] in BASE]
            rows.append((*[sum(s[0] == k for s in base) for k in BASE], digest(render(base, KINDS)), render(found, KINDS)))
        cols = list(zip(*rows, strict=True)) or [()] * 6
        return pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(c, pa.int64()) for c in cols[:4]], *[pa.array(c, pa.string()) for c in cols[4:]]], ["doc_id", *[f"n_{k}" for k in BASE], "base_sha256", "spans"])

    return map_batches(documents(docs), fn, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string")
