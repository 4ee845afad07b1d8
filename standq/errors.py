"""Errors of the engine."""


class StandingQueryError(Exception):
    """Base of all errors below."""


class ConstraintViolation(StandingQueryError):
    """DML breaks a property of its table."""


class ConcurrentCommit(StandingQueryError):
    """Another transaction took the commit number; run the transaction again."""


class NotInsertOnly(StandingQueryError):
    """A continuous cursor needs a relation that is proven insert-only."""


class Dependent(StandingQueryError):
    """A property cannot be removed while an open cursor depends on it."""


class ExpiredData(StandingQueryError):
    """A query reads rows that are expired or purged and asked not to."""


class UnboundedState(StandingQueryError):
    """FINAL over a window would never let go of its ranges."""


class IllegalTransition(StandingQueryError):
    """A task cannot go from this state to that one."""


class NotMonotone(StandingQueryError):
    """A predicate may turn from true to false."""


class RejectLimit(StandingQueryError):
    """More rows were rejected than the task allows."""
