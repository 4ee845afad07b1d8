"""Change, cursor, task, window, finality and expiry operators."""
