"""Continuous cursors, ordinary cursors for contrast, and subscriptions."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass
from datetime import datetime
from typing import Any

from pyspark.sql import DataFrame

from standq.errors import NotInsertOnly, StandingQueryError
from standq.plans.relation import Changes, Relation, simplify


def moment(v: Any) -> datetime:
    """A commit's time, which a manifest that was read has as text."""
    return v if isinstance(v, datetime) else datetime.fromisoformat(v)


@dataclass
class Fetch:
    df: DataFrame
    status: str
    after: int
    upto: int


class ContinuousCursor:
    """A forward-only bookmark over an insert-only relation, kept across transactions, that shows committed rows alone.

    The reader owns its bookmark: a commit number in a file of its own, written when a fetch is acknowledged (``commit``)
    or at the next fetch. The first fetch gives all rows, a later one those committed since.
    """

    def __init__(self, rel: Relation, name: str | None = None, start_at: int | str | datetime = "beginning", with_return: bool = False, strict_syntax: bool = False, yet_status: bool = False, rules: str = "paper"):
        self.rel = simplify(rel).rel
        if strict_syntax and not isinstance(rel, Changes):
            raise NotInsertOnly("the cursor's source must be CHANGES of a relation")
        ok, why = self.rel.insert_only(rules)
        if not ok:
            raise NotInsertOnly(why)
        self.db, self.name = rel.db, name or f"cursor_{uuid.uuid4().hex[:8]}"
        self.with_return, self.yet_status, self.open = with_return, yet_status, True
        self.file = f"_cursors/{self.name}.json"
        kept = self.db.log.get(self.file)
        self.bookmark = kept["last_commit_no"] if kept else self._start(start_at)
        self.db.cursors[self.name] = self.rel.tables()
        self.pending: int | None = None

    def _start(self, at: int | str | datetime) -> int:
        """``beginning``, ``now``, a commit, or a time: after the last commit that is not later."""
        if isinstance(at, datetime):
            return max((m["commit"] for m in self.db.manifests if moment(m["time"]) <= at), default=0)
        return 0 if at == "beginning" else self.db.version if at == "now" else int(at)

    def _admitted(self, max_commits: int | None, max_rows: int | None) -> int:
        """The last commit of a fetch: whole commits, at least one of the source's, and no more than asked for."""
        upto = self.db.refresh()
        if max_commits is not None:
            upto = min(upto, self.bookmark + max_commits)
        if max_rows is not None:
            held, tables = 0, self.rel.tables()
            for m in self.db.manifests[self.bookmark : upto]:
                n = sum(e["inserts"] + e["updates"] + e["deletes"] for t, e in m["tables"].items() if t in tables)
                if held and held + n > max_rows:
                    return m["commit"] - 1
                held += n
        return upto

    def fetch(self, max_commits: int | None = None, max_rows: int | None = None) -> Fetch:
        """Rows of whole commits after the bookmark, as many as hold at most ``max_rows`` records of the source (one commit
        at least); the caller acknowledges by the next fetch or ``commit``."""
        if not self.open:
            raise StandingQueryError(f"cursor {self.name} is closed")
        self.commit()
        upto = self._admitted(max_commits, max_rows)
        if self.bookmark and not isinstance(self.rel, Changes):
            for t in self.rel.tables():
                if not self.db.table(t).only_inserts(upto, self.bookmark):
                    raise NotInsertOnly(f"{t} was changed by other than inserts after commit {self.bookmark}, before it was declared insert-only")
        moved = self.bookmark == 0 and upto > 0 or bool(self.rel.tables() & self.db.changed(self.bookmark, upto))
        if not moved:
            rows = self.rel.at(0).drop("_row_id")
            status = "NO_DATA_YET" if self.yet_status else "NO_DATA"
        elif self.bookmark == 0:
            rows, status = self.rel.at(upto).drop("_row_id"), "OK"
        else:
            rows, status = self.rel.delta(self.bookmark, upto).drop("_row_id", "_sign"), "OK"
        out = Fetch(rows, status, self.bookmark, upto)
        self.pending = upto
        return out

    def commit(self) -> None:
        if self.pending is not None:
            self.bookmark, self.pending = self.pending, None
            self.db.log.replace(self.file, {"last_commit_no": self.bookmark})

    def close(self) -> None:
        self.commit()
        self.open = False
        self.db.cursors.pop(self.name, None)


class SnapshotCursor:
    """An ordinary cursor: pages of an ordered result, in any direction if it may scroll; pinned to a version unless it is
    sensitive to later commits."""

    def __init__(self, rel: Relation, order_by: list[str], sensitive: bool = False, scroll: bool = True, with_return: bool = False):
        self.rel, self.order, self.sensitive, self.scroll, self.with_return = rel, order_by, sensitive, scroll, with_return
        self.version, self.at, self.pinned = rel.db.version, 0, None

    def _rows(self) -> DataFrame:
        if self.sensitive:
            self.version, self.pinned = self.rel.db.refresh(), None
        if self.pinned is None:
            self.pinned = self.rel.to_df(self.version)
        return self.pinned

    def _page(self, start: int, n: int) -> DataFrame:
        """Pages follow a total order, as a cursor must; Spark keeps the first rows of each task, or sorts by ranges."""
        self.at = start + n - 1
        return self._rows().orderBy(*self.order).offset(start - 1).limit(n)

    def next(self, n: int = 1) -> DataFrame:
        return self._page(self.at + 1, n)

    def _scrolling(self) -> None:
        if not self.scroll:
            raise StandingQueryError("the cursor does not scroll")

    def first(self) -> DataFrame:
        self._scrolling()
        return self._page(1, 1)

    def last(self) -> DataFrame:
        self._scrolling()
        return self._page(self._rows().count(), 1)

    def prior(self) -> DataFrame:
        self._scrolling()
        return self._page(max(1, self.at - 1), 1)


class Subscription:
    """An implicit cursor and endless fetches, on a schedule (each commit by default), until cancelled."""

    def __init__(self, rel: Relation, on_rows: Callable[[DataFrame], None], schedule: Any = None, **options: Any):
        from standq.operators.task import OnCommit, Scheduler

        self.cursor, self.on_rows = ContinuousCursor(rel, **options), on_rows
        self.schedule = schedule or OnCommit()
        self.scheduler = Scheduler.of(rel.db)
        self.scheduler.add(self)
        self.fetches = 0
        self.run_now()

    @property
    def name(self) -> str:
        return self.cursor.name

    def sources(self) -> set[str]:
        return self.cursor.rel.tables()

    def run_now(self) -> str:
        got = self.cursor.fetch()
        if got.status == "OK":
            self.on_rows(got.df)
            self.fetches += 1
        self.cursor.commit()
        return got.status

    def cancel(self) -> None:
        self.scheduler.remove(self)
        self.cursor.close()
