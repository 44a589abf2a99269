"""Pattern text as columns."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from canopy.pattern.canonical import canonical_form, code, is_canonical
from canopy.pattern.codec import parse, show
from canopy.pattern.morph import embeds, find_root_images


@F.pandas_udf(T.IntegerType())
def p_size(text: pd.Series) -> pd.Series:
    return text.map(lambda t: parse(t).size)


@F.pandas_udf(T.IntegerType())
def p_depth(text: pd.Series) -> pd.Series:
    return text.map(lambda t: parse(t).depth)


@F.pandas_udf(T.IntegerType())
def p_fanout(text: pd.Series) -> pd.Series:
    return text.map(lambda t: parse(t).fanout)


@F.pandas_udf(T.IntegerType())
def p_leaves(text: pd.Series) -> pd.Series:
    return text.map(lambda t: len(parse(t).leaves))


@F.pandas_udf(T.ArrayType(T.StringType()))
def p_labels(text: pd.Series) -> pd.Series:
    return text.map(lambda t: sorted(parse(t).labels))


@F.pandas_udf(T.BooleanType())
def p_is_path(text: pd.Series) -> pd.Series:
    return text.map(lambda t: parse(t).is_path)


@F.pandas_udf(T.StringType())
def p_code(text: pd.Series) -> pd.Series:
    """Canonical text."""
    return text.map(lambda t: code(parse(t)))


@F.pandas_udf(T.StringType())
def p_prefix(text: pd.Series) -> pd.Series:
    """The immediate prefix of the canonical form; null for a single node."""
    return text.map(lambda t: show(p.prefix()) if (p := canonical_form(parse(t))).size > 1 else None)


@F.pandas_udf(T.BooleanType())
def p_canonical(text: pd.Series) -> pd.Series:
    return text.map(lambda t: is_canonical(parse(t)))


@F.pandas_udf(T.BooleanType())
def p_embeds(small: pd.Series, large: pd.Series) -> pd.Series:
    return pd.Series([embeds(parse(p), parse(q)) for p, q in zip(small, large)], dtype=bool)


@F.pandas_udf(T.ArrayType(T.IntegerType()))
def p_root_images(small: pd.Series, large: pd.Series) -> pd.Series:
    return pd.Series([sorted(find_root_images(parse(p), parse(q))) for p, q in zip(small, large)], dtype=object)


def label_multiset(labels: Column) -> Column:
    """An array of labels as a map of counts."""
    kinds = F.array_distinct(labels)
    return F.map_from_arrays(kinds, F.transform(kinds, lambda x: F.size(F.filter(labels, lambda y: y == x))))
