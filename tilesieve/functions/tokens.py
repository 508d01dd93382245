"""Tokens of a learnt tokenizer, as arrays that token filters take."""

from __future__ import annotations

import json
import re
import unicodedata
from collections.abc import Iterator
from itertools import chain

import pandas as pd
from pyspark.sql import functions as F

_LOADED: dict[str, tuple] = {}


#: Pieces of texts whose tokens a worker remembers.
PIECES = 1 << 18
#: Characters below this have fixed classes; texts with others are left to the library.
KNOWN = 0x250


def _pieces() -> tuple[re.Pattern, re.Pattern]:
    """The pieces that a byte-level tokenizer merges each for itself, and the characters that are not known here."""
    cls = lambda kinds: "".join(f"\\u{i:04x}" for i in range(KNOWN) if unicodedata.category(chr(i))[0] in kinds)
    letters, numbers, blanks = cls("L"), cls("N"), r"\t-\r \x85\xa0"
    known = rf"'(?:[stmd]|re|ve|ll)| ?[{letters}]+| ?[{numbers}]+| ?[^{blanks}{letters}{numbers}]+|[{blanks}]+(?![^{blanks}])|[{blanks}]+"
    return re.compile(known), re.compile(rf"[^\x00-\u{KNOWN - 1:04x}]|[\x1c-\x1f]")


def _letters_of_bytes() -> dict[int, str]:
    """Byte-level BPE writes each byte as a character that can be seen: Latin-1 itself where that is one, others from 256 on."""
    seen = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    return {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in seen)}


def local_tokens(path: str):
    """A function of a worker: texts -> lists of token ids as strings, by a definition file that executors can open.

    Null texts give null. The library is loaded in the tasks only, once for each worker. Where the definition is
    plain byte-level BPE, its model is asked for each different piece once, and the library for whole texts only where
    characters or added tokens leave the pieces in doubt.
    """

    def load():
        import os

        from tokenizers import Tokenizer

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        tokenizer = Tokenizer.from_file(path)
        shape = json.loads(tokenizer.to_str())
        pre, model = shape["pre_tokenizer"] or {}, shape["model"]
        plain = pre.get("type") == "ByteLevel" and pre.get("use_regex") and not pre.get("add_prefix_space") and not shape["normalizer"] and model["type"] == "BPE" and not model.get("dropout") and not shape["truncation"] and not shape["padding"]
        return tokenizer, [str(i) for i in range(1 + max(tokenizer.get_vocab().values()))], plain, [t["content"] for t in shape["added_tokens"]], *_pieces(), {}

    def cut(texts: list[str | None]) -> Iterator[list[str] | None]:
        if path not in _LOADED:
            _LOADED[path] = load()
        tokenizer, names, plain, added, pieces, unknown, seen = _LOADED[path]
        whole = lambda t: [names[i] for i in tokenizer.encode_batch_fast([t], add_special_tokens=False)[0].ids]
        model, letters = tokenizer.model, _letters_of_bytes()
        for t in texts:
            if t is None:
                yield None
            elif not plain or unknown.search(t) or any(x in t for x in added):
                yield whole(t)
            else:
                found = pieces.findall(t)
                parts = list(map(seen.get, found))
                if None in parts:
                    if len(seen) > PIECES:
                        seen.clear()
                    for i, x in enumerate(found):
                        if parts[i] is None:
                            if (some := seen.get(x)) is None:
                                some = seen[x] = tuple([names[y.id] for y in model.tokenize(x.encode().decode("latin-1").translate(letters))])
                            parts[i] = some
                yield list(chain.from_iterable(parts))

    return cut


def library_tokens(path: str):
    """A column function: text -> array of token ids as strings, for tables of few texts."""
    local = local_tokens(path)

    @F.pandas_udf("array<string>")
    def cut(texts: pd.Series) -> pd.Series:
        return pd.Series(list(local([t if isinstance(t, str) else None for t in texts])))

    return cut
