"""User-defined functions that have native twins: seams for endpoints and checks that both ways agree."""

from __future__ import annotations

import re
import unicodedata
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.pandas_udf(T.StringType())
def normalize_udf(names: pd.Series) -> pd.Series:
    """The rule of functions.text.normalize_name, over Arrow batches."""
    from catalogflow.functions.text import ACCENTED, PLAIN

    table = str.maketrans(ACCENTED, PLAIN)
    return names.map(lambda x: None if x is None else re.sub("[^a-z0-9]+", " ", unicodedata.normalize("NFC", x.lower()).translate(table)).strip(" "))


@F.pandas_udf(T.DoubleType())
def mean_f1(gold: pd.Series, pred: pd.Series) -> float:
    """Mean over rows of F1 between 0/1 flags: a grouped aggregate."""
    both, total = ((gold == 1) & (pred == 1)).astype(float), gold + pred
    return float((2 * both / total.where(total > 0, 1)).where(total > 0, 1.0).mean())


@F.udtf(returnType=T.StructType([T.StructField("kind", T.StringType()), T.StructField("value", T.StringType())]))
class PageElements:
    """Elements of a page: its title and every link."""

    def eval(self, html: str) -> Iterator[tuple[str, str]]:
        if html:
            for kind, pattern in (("title", "<title>([^<]*)</title>"), ("href", 'href="([^"]*)"')):
                for m in re.findall(pattern, html):
                    yield kind, m


def pack_group(pdf: pd.DataFrame, budget: int) -> pd.DataFrame:
    """Next fit over one group, in order: the twin of operators.classify.pack_prompts for very large groups."""
    pdf = pdf.sort_values("ord")
    no, used, out = 0, budget + 1, []
    for n in pdf["chars"]:
        if used + n <= budget:
            used += n
        else:
            no, used = no + 1, n
        out.append(no)
    return pdf.assign(prompt_no=out)[["grp", "ord", "prompt_no"]]
