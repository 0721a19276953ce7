"""SQL surface: code functions, views of a summary, and a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from glyphfold.functions.bits import register_sql
from glyphfold.operators.summary import Summary, register_views


@udtf(returnType="src: long, dst: long")
class ExpandSupernode:
    """Edges that a glyph stands for: ``SELECT * FROM expand_supernode(glyph, hub, ids)``."""

    def eval(self, glyph: str, hub: int, ids: list):
        if glyph == "clique":
            yield from ((u, v) for u in ids for v in ids if u != v)
        elif glyph == "in_star":
            yield from ((u, hub) for u in ids if u != hub)
        elif glyph == "out_star":
            yield from ((hub, u) for u in ids if u != hub)


def register(spark: SparkSession, s: Summary | None = None, name: str = "graph") -> None:
    """Code functions, ``expand_supernode``, and the views of ``s`` under ``name``."""
    register_sql(spark)
    spark.udtf.register("expand_supernode", ExpandSupernode)
    if s is not None:
        register_views(s, name)
