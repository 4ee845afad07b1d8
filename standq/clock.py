"""Clocks. Everything that asks for the time takes one, so that traces can be repeated."""

from __future__ import annotations

from datetime import datetime, timedelta, timezone


class SystemClock:
    def now(self) -> datetime:
        return datetime.now(timezone.utc).replace(tzinfo=None)


class ManualClock:
    def __init__(self, start: datetime = datetime(2024, 1, 1)):
        self.at = start

    def now(self) -> datetime:
        return self.at

    def advance(self, **by: float) -> datetime:
        self.at += timedelta(**by)
        return self.at
