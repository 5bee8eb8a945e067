"""When does a neighbour's new estimate matter to a vertex?"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

GATES = ("all", "lower", "support", "counter")


def gate(kind: str, new: str = "new", old: str = "old", mine: str = "est") -> Column:
    """Predicate on a message (``old`` to ``new``) and the receiver's estimate ``mine``.

    all: always. lower: the new value is below mine. support: also, the old value was not, so the sender did support me.
    ``mine`` may be of before or after the round for ``lower``, but must be of after it for ``support``: against a value
    from before the round a sender may look useless that the receiver's lowered estimate relies on.
    """
    if kind == "all":
        return F.lit(True)
    lower = F.col(new) < F.col(mine)
    if kind == "lower":
        return lower
    if kind in ("support", "counter"):
        return lower & (F.col(old) >= F.col(mine))
    raise ValueError(f"gate {kind!r}: one of {GATES}")
