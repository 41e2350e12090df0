"""Limits that a baseline fails at, as a defined outcome."""

from __future__ import annotations


class BudgetExceeded(RuntimeError):
    """kind: rows, edges or frame; at: where; needed against allowed."""

    def __init__(self, kind: str, at: str, needed: int, allowed: int) -> None:
        super().__init__(f"{kind} at {at}: {needed} beyond {allowed}")
        self.kind, self.at, self.needed, self.allowed = kind, at, needed, allowed


def within(kind: str, at: str, needed: int, allowed: int | None) -> None:
    if allowed is not None and needed > allowed:
        raise BudgetExceeded(kind, at, needed, allowed)
