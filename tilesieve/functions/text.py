"""Text normalisation. Patterns are written so that Java's and RE2's engines agree."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

BLANKS = r"[ \t\n\r\f]+"
MODES = ("collapse", "remove", "line_indent", "none")


def normalize(text: Column, mode: str = "collapse") -> Column:
    """White space of a text: ``collapse`` runs to one blank and trim, ``remove`` all, drop each line's
    ``line_indent``, or ``none``. A filter and its queries must use the same mode."""
    if mode == "collapse":
        return F.trim(F.regexp_replace(text, BLANKS, " "))
    if mode == "remove":
        return F.regexp_replace(text, BLANKS, "")
    if mode == "line_indent":
        return F.regexp_replace(text, r"(^|\n)[ \t]+", "$1")
    if mode == "none":
        return text
    raise ValueError(f"mode must be one of {MODES}")


def detokenize(text: Column) -> Column:
    """Close up blanks before ``, . ; : ! ? ) ] }`` and after ``( [ {``."""
    return F.regexp_replace(F.regexp_replace(text, r" +([,.;:!?)\]}])", "$1"), r"([(\[{]) +", "$1")


def tokenize_punct(text: Column) -> Column:
    """Set off the same marks by blanks: the reverse of ``detokenize``."""
    return F.trim(F.regexp_replace(F.regexp_replace(text, r"([,.;:!?)\]}(\[{])", " $1 "), " +", " "))


def page_text(html: Column) -> Column:
    """Visible text of a page: comments, scripts, styles and tags out, common entities decoded, blanks collapsed."""
    c = F.regexp_replace(html, r"(?s)<!--.*?-->", " ")
    c = F.regexp_replace(c, r"(?is)<script.*?</script>", " ")
    c = F.regexp_replace(c, r"(?is)<style.*?</style>", " ")
    c = F.regexp_replace(c, r"(?s)<[^>]*>", " ")
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        c = F.replace(c, F.lit(entity), F.lit(char))
    return normalize(c)


def page_language(url: Column) -> Column:
    """Two-letter language in a URL's path; empty if none."""
    return F.regexp_extract(url, r"/([a-z][a-z])/", 1)


def offset_map(text: Column) -> Column:
    """For each character of the collapsed text, where it stands in the raw one: spans lead back to the original."""

    @F.pandas_udf("array<int>")
    def places(texts: pd.Series) -> pd.Series:
        def one(t):
            if t is None:
                return None
            out, blank = [], re.compile(BLANKS)
            at = 0
            while at < len(t):
                run = blank.match(t, at)
                if run is None:
                    out.append(at)
                    at += 1
                else:
                    out.append(at)
                    at = run.end()
            kept = [c if not blank.match(c) else " " for c in (t[i] for i in out)]
            a, b = 0, len(out)
            while a < b and kept[a] == " ":
                a += 1
            while b > a and kept[b - 1] == " ":
                b -= 1
            return out[a:b]

        return texts.map(one)

    return places(text)
