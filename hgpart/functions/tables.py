"""Table functions; apart from the others, as workers import this module."""

from __future__ import annotations

from pyspark.sql.functions import udtf


@udtf(returnType="n long, m long")
class CoPins:
    """All pairs n before m of one packed set."""

    def eval(self, items):
        for i, n in enumerate(items):
            for m in items[i + 1 :]:
                yield n, m
