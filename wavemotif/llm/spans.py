"""Spans in texts as rows: kind, start, end in code points, end exclusive; their text form and digest."""

from __future__ import annotations

import hashlib

Span = tuple[str, int, int]


def render(spans: list[Span], kinds: tuple[str, ...]) -> str:
    """kind:start:end by start, then in the order of kinds, comma-joined."""
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(set(spans), key=lambda s: (s[1], kinds.index(s[0]), s[2])))


def digest(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()
