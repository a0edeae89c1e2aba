"""The 27 path modes: a selector (or none) with a restrictor."""

from __future__ import annotations

import re
from dataclasses import dataclass

SELECTORS = ("ALL", "ANY", "ANY SHORTEST", "ALL SHORTEST", "ANY K", "SHORTEST K", "SHORTEST K GROUPS")
RESTRICTORS = ("WALK", "TRAIL", "SIMPLE", "ACYCLIC")


class PathModeError(ValueError):
    pass


@dataclass(frozen=True)
class PathMode:
    selector: str
    restrictor: str
    k: int = 1

    def __post_init__(self):
        if self.selector not in SELECTORS or self.restrictor not in RESTRICTORS:
            raise PathModeError(f"no such mode: {self.selector} {self.restrictor}")
        if self.selector == "ALL" and self.restrictor == "WALK":
            raise PathModeError("WALK needs a selector: there can be infinitely many walks")
        if self.k < 1:
            raise PathModeError("k is 1 or more")

    @property
    def counts_paths(self) -> bool:
        """Whether a path must be found once only, so that the automaton must be unambiguous."""
        return self.selector not in ("ANY", "ANY SHORTEST")

    @property
    def determined(self) -> bool:
        """Whether the definition leaves no choice of answers."""
        return self.selector in ("ALL", "ALL SHORTEST", "SHORTEST K GROUPS")

    def __str__(self) -> str:
        return f"{'' if self.selector == 'ALL' else self.selector.replace('K', str(self.k), 1) if ' K' in self.selector else self.selector} {self.restrictor}".strip()


def parse_mode(text: str, k: int | None = None) -> PathMode:
    """'SHORTEST 3 GROUPS TRAIL', 'any walk', 'TRAIL', 'SHORTEST k WALK' with k given, plural restrictors."""
    words = [w.rstrip("S") if w in ("WALKS", "TRAILS") else w for w in text.upper().split()]
    number = next((int(w) for w in words if w.isdigit()), k)
    words = ["K" if re.fullmatch(r"\d+|K", w) else w for w in words]
    if not words:
        raise PathModeError("empty mode")
    selector = " ".join(words[:-1]) or "ALL"
    if " K" in f" {selector}" and number is None:
        raise PathModeError(f"{text}: k is missing")
    return PathMode(selector, words[-1], 1 if number is None else number)


ALL_MODES = tuple(PathMode(s, r, 2) for r in RESTRICTORS for s in SELECTORS if (s, r) != ("ALL", "WALK"))
