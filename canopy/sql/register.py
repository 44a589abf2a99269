"""Pattern functions and table functions for SQL."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from canopy.functions import patterns
from canopy.pattern.canonical import code
from canopy.pattern.codec import parse, show
from canopy.pattern.expand import expand_class
from canopy.pattern.morph import one_smaller


@udtf(returnType="code string, k int")
class Subpatterns:
    """All embedded subpatterns of a pattern, itself included."""

    def eval(self, text: str):
        todo, seen = [parse(text)], set()
        while todo:
            p = todo.pop()
            c = code(p)
            if c not in seen:
                seen.add(c)
                yield c, p.size
                todo += one_smaller(p)


@udtf(returnType="left_code string, right_code string, kind string, code string")
class ExpandClass:
    """Join results of the members of a class, given as texts parted by ``;``."""

    def eval(self, members: str):
        for x, y, kind, q in expand_class([parse(t.strip()) for t in members.split(";")]):
            yield show(x), show(y), kind, show(q)


def register(spark: SparkSession) -> None:
    """``p_*`` functions, and the table functions ``subpatterns`` and ``expand_class``."""
    for name in ("p_size", "p_depth", "p_fanout", "p_leaves", "p_labels", "p_is_path", "p_code", "p_prefix", "p_canonical", "p_embeds", "p_root_images"):
        spark.udf.register(name, getattr(patterns, name))
    spark.udtf.register("subpatterns", Subpatterns)
    spark.udtf.register("expand_class", ExpandClass)


def match(spark: SparkSession, view: str, text: str, kind: str = "emb", what: str = "roots"):
    """A twig query against a registered ``nodes`` view."""
    from canopy.match.twig import find

    return find(spark.table(view), text, kind, what)
