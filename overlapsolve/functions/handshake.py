"""The coarse handshake's state machine, and the adaptive pause between its polls."""

from __future__ import annotations

import uuid
from dataclasses import dataclass
from pathlib import Path


class Counters(dict):
    """Counts in memory; what was never set is 0. Live runs keep them in files."""

    def __missing__(self, key: str) -> int:
        return 0


class FileCounters:
    """Counts in files of a folder that all tasks see; each is replaced as a whole."""

    def __init__(self, root: Path):
        self.root = root
        root.mkdir(parents=True, exist_ok=True)

    def __getitem__(self, key: str) -> int:
        try:
            return int((self.root / key).read_text() or 0)
        except FileNotFoundError:
            return 0

    def __setitem__(self, key: str, value: int) -> None:
        temp = self.root / f"{key}.{uuid.uuid4().hex}"
        temp.write_text(str(value))
        temp.replace(self.root / key)


class CoarseHandshake:
    """Who may post a share, when the coarse solver may go, and who has a correction to use. Payloads are the caller's.

    A part may post as often as the coarse solver has solved, and once more. Order: a payload is written before its post or
    solve is counted, and a count is read before its payload; hence may_post, can_solve and has_correction come apart from
    posted, solved and consumed, and the try_ forms do both at once.
    """

    def __init__(self, parts: int, strict: bool = False, counts=None):
        self.parts, self.strict, self.counts, self.lost = parts, strict, Counters() if counts is None else counts, 0

    @property
    def solves(self) -> int:
        return self.counts["solved"]

    def may_post(self, p: int) -> bool:
        """Whether p may write its share now; with strict, not while a correction waits to be used."""
        return self.counts[f"posted{p}"] == self.solves and not (self.strict and self.has_correction(p))

    def posted(self, p: int) -> None:
        self.counts[f"posted{p}"] = self.counts[f"posted{p}"] + 1

    def can_solve(self) -> bool:
        done = self.solves
        return all(self.counts[f"posted{p}"] > done for p in range(self.parts))

    def solved(self) -> None:
        """Counted after the corrections are written; shares are then read no more, and posting is allowed again."""
        self.lost += sum(self.has_correction(p) for p in range(self.parts))
        self.counts["solved"] = self.solves + 1

    def has_correction(self, p: int) -> bool:
        return self.counts[f"consumed{p}"] < self.solves

    def consumed(self, p: int) -> None:
        self.counts[f"consumed{p}"] = self.solves

    def try_post(self, p: int) -> bool:
        may = self.may_post(p)
        if may:
            self.posted(p)
        return may

    def try_solve(self) -> bool:
        can = self.can_solve()
        if can:
            self.solved()
        return can

    def try_consume(self, p: int) -> bool:
        """True once for each correction that arrives at p."""
        has = self.has_correction(p)
        if has:
            self.consumed(p)
        return has


@dataclass
class AdaptiveSleep:
    """Keeps performed solves to about `target` of the attempted ones: longer pauses if polls fail more often, shorter if less."""

    target: float = 1 / 20
    gain: float = 1.25
    pause: float = 1e-3
    least: float = 1e-5
    most: float = 1.0
    attempts: int = 0
    performed: int = 0

    def poll(self, success: bool) -> float:
        """Count a poll; the pause to make after it if it failed, in seconds."""
        self.attempts += 1
        self.performed += success
        if success or self.attempts % 20 == 0:
            ratio = self.performed / self.attempts
            self.pause = min(self.most, max(self.least, self.pause * (self.gain if ratio < self.target else 1 / self.gain)))
            if self.attempts > 400:
                self.attempts, self.performed = self.attempts // 2, self.performed // 2
        return 0.0 if success else self.pause

    @property
    def ratio(self) -> float:
        return self.performed / self.attempts if self.attempts else 0.0
