"""A bounded memo for Python workers; it lives as long as its worker and never changes a result."""

from __future__ import annotations

from collections.abc import Callable


_LIVE: list["Memo"] = []


def only(*kept: "Memo") -> None:
    """Empty all other memos of this worker. Workers serve one operator after the other, and only the one at work should hold memory."""
    for memo in _LIVE:
        if not any(memo is k for k in kept):
            memo.clear()
            memo.older = {}


class Memo(dict):
    """``memo[key]`` is ``make(key)``, remembered for keys of at most ``longest`` characters.

    When ``room`` keys are held they become the older half, from which keys that are asked for again come back; what was there before goes.
    """

    def __init__(self, make: Callable, room: int = 300_000, longest: int = 48):
        super().__init__()
        self.make, self.room, self.longest = make, room, longest
        self.older: dict = {}
        _LIVE.append(self)

    def __missing__(self, key):
        value = self.older.get(key)
        if value is None:
            value = self.make(key)
            if len(key) > self.longest:
                return value
        if len(self) >= self.room:
            self.older = dict(self)
            self.clear()
        self[key] = value
        return value
