"""Table functions for SQL users."""

from __future__ import annotations

from pyspark.sql.functions import udtf

from tripleschema.model import LAMBDA


def expand_pattern():
    """``expand_pattern(s, p, o)``: the eight variants of an atom with the fresh IRI at any of its places."""
    fresh = LAMBDA

    @udtf(returnType="s string, p string, o string")
    class Expand:
        def eval(self, s: str, p: str, o: str):
            for k in range(8):
                yield (fresh if k & 4 else s, fresh if k & 2 else p, fresh if k & 1 else o)

    return Expand
