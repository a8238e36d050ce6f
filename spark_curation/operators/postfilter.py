"""Records into which the syntax of operations leaked."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LEAK = r"(?m)<(?:extract|keep|delete|edit|rewrite)>|<lid:[0-9]+>|^[ \t]*rm [0-9]+(?:-[0-9]+)?[ \t]*$|^[ \t]*sub [0-9]+: ?\""


def leaked(col: str = "text") -> F.Column:
    return F.coalesce(F.col(col).rlike(LEAK), F.lit(False))


def reject_leaks(executed: DataFrame, col: str = "text") -> DataFrame:
    """Records whose text shows no program syntax."""
    return executed.where(~leaked(col))
