"""Rows whose further columns travel through an operator unseen, whatever their names are.

An operator's own columns get its names, all others go into one struct by position, so that no name of theirs (dots, other case, the operator's own private names) meets one of the operator's.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F


class Carried:
    """``rows`` has the columns ``own`` (found without regard to case) and ``payload``; ``back`` gives the columns of ``df`` again, in their order, without those whose names are ``taken`` by results. ``made`` are further columns of ``rows``, computed on ``df``.
    """

    def __init__(self, df: DataFrame, *own: str, taken: tuple[str, ...] = (), **made: Column):
        lower = [c.lower() for c in df.columns]
        at = {}
        for o in own:
            found = [i for i, c in enumerate(df.columns) if c == o] or [i for i, c in enumerate(lower) if c == o.lower()]
            if not found:
                raise ValueError(f"no column {o} among {df.columns}")
            at[found[0]] = o
        gone = {t.lower() for t in taken}
        self.order = [(i, c, at.get(i)) for i, c in enumerate(df.columns) if i in at or lower[i] not in gone]
        wide = df.select("*", *made.values()) if made else df
        plain = wide.toDF(*[f"c{i}" for i in range(len(lower))], *made)
        rest = [F.col(f"c{i}") for i, _, o in self.order if o is None]
        self.rows = plain.select(*[F.col(f"c{i}").alias(o) for i, o in at.items()], *made, F.struct(*rest or [F.lit(0).alias("none")]).alias("payload"))

    def back(self, **instead: Column) -> list[Column]:
        """The original columns out of rows that still have ``own`` and ``payload``; ``instead`` replaces some of ``own``."""
        return [(instead.get(o, F.col(o)) if o else F.col(f"payload.c{i}")).alias(c) for i, c, o in self.order]
