"""Secret scans with multipart credential linking.

Base spans (assignments, access identifiers, long hex runs) are always reported. Weaker parts
(identifiers, opaque tokens, endpoints) mean little alone: an interval join inside each scope, one
sweep over the parts by position, reports them only where complementary parts co-occur.
"""

from __future__ import annotations

import bisect
import hashlib
import itertools
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from tilesieve.llm.common import frugal, ship, text_slices

ship(__name__)

BASE_KINDS = ("assign", "access", "hex")
LINKED_KINDS = ("identity", "opaque", "endpoint")
KINDS = BASE_KINDS + LINKED_KINDS

#: Fixed patterns of the base kinds.
ASSIGN = re.compile(r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
LEAST = {"assign": 6, "access": 20}

IDENTITY = re.compile(r"""(?:user(?:name|id)?|login|account(?:_id)?|client_id|access_key(?:_id)?)["']?\x20*[:=]\x20*["']?[A-Za-z0-9][A-Za-z0-9._@+-]{2,}""", re.IGNORECASE | re.ASCII)
OPAQUE = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}={0,2}(?![A-Za-z0-9+/_-])")
# a host begins where no host character stands before, and its labels give nothing back: no text is tried twice
ENDPOINT = re.compile(r"""[a-z][a-z0-9+]{1,15}://[^\x00-\x20"'<>]{3,}|(?<![a-z0-9.-])[a-z0-9-]++(?:\.[a-z0-9-]++)++:[0-9]{2,5}\b""")
BREAK = re.compile(r"\n[\x20\t\r]*\n")

#: Parts further apart than this, in code points, or in different paragraphs, are never linked.
SCOPE = 400
#: Bits a character that an opaque token must reach; prose words stay below.
LEAST_ENTROPY = 3.5

Span = tuple[int, int, str]


def base_spans(text: str) -> list[Span]:
    """Assignments, access identifiers and hex runs as (start, end, kind), by start, then kind."""
    found = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST["access"]]
    found += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


def _entropy(token: str) -> float:
    n = len(token)
    return -sum(c / n * math.log2(c / n) for c in (token.count(x) for x in set(token)))


def weak_parts(text: str) -> list[Span]:
    """Identifiers, opaque tokens and endpoints: candidates that count only when linked."""
    found = [(m.start(), m.end(), "identity") for m in IDENTITY.finditer(text)] if ":" in text or "=" in text else []
    found += [(m.start(), m.end(), "opaque") for m in OPAQUE.finditer(text) if re.search("[0-9]", t := m[0]) and re.search("[A-Za-z]", t) and _entropy(t) >= LEAST_ENTROPY]
    if ":" in text:
        found += [(m.start(), m.end(), "endpoint") for m in ENDPOINT.finditer(text)]
    return found


ROLE = {"assign": "secret", "hex": "secret", "opaque": "secret", "access": "identity", "identity": "identity", "endpoint": "endpoint"}


def linked_parts(text: str, base: list[Span], weak: list[Span], scope: int = SCOPE) -> list[Span]:
    """Weak parts that have a complementary part, weak or not, within their scope.

    A secret is completed by an identity or an endpoint, and either of those by a secret. For each
    part the nearest part of each role before and after it is enough, so the sweep is linear.
    """
    if not weak:
        return []
    taken = sorted((a, b) for a, b, _ in base)
    begins = [a for a, _ in taken]
    reach = list(itertools.accumulate((b for _, b in taken), max))

    def covered(a: int, b: int) -> bool:
        i = bisect.bisect_right(begins, b - 1)
        return i > 0 and reach[i - 1] > a

    parts = sorted(base + [s for s in weak if not (s[2] == "opaque" and covered(s[0], s[1]))])
    breaks = [m.start() for m in BREAK.finditer(text)]
    near: list[bool] = [False] * len(parts)
    for order in (range(len(parts)), range(len(parts) - 1, -1, -1)):
        last: dict[str, Span] = {}
        for i in order:
            a, b, kind = parts[i]
            role = ROLE[kind]
            for other in ("identity", "endpoint") if role == "secret" else ("secret",):
                if (o := last.get(other)) and max(a, o[0]) - min(b, o[1]) <= scope and bisect.bisect_right(breaks, min(a, o[0])) == bisect.bisect_right(breaks, max(a, o[0])):
                    near[i] = True
            # forwards the part that ends last is nearest to what follows; backwards each part starts before those seen
            if order.step < 0 or role not in last or b > last[role][1]:
                last[role] = parts[i]
    return [s for s, hit in zip(parts, near, strict=True) if hit and s[2] in LINKED_KINDS]


def scan(text: str | None, scope: int = SCOPE) -> tuple[list[Span], list[Span]]:
    """Base spans, and all spans with the linked ones."""
    text = text or ""
    base = base_spans(text)
    every = base + linked_parts(text, base, weak_parts(text), scope)
    return base, sorted(set(every), key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def digest(spans: list[Span]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for a, b, kind in spans)


SCHEMA = "doc_id bigint, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string, n_linked bigint"


def find_secrets(df: DataFrame, *, scope: int = SCOPE) -> DataFrame:
    """Secrets of every whole text, a row for each document.

    Offsets are code points, ends exclusive. ``base_sha256`` is over the joined base spans,
    ``spans`` joins all spans. Null and empty texts have no spans; repeated rows and null ids are
    kept as they are; an empty table gives no rows; other columns are left out.
    """

    @frugal
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in text_slices(batch):
                out: list[tuple] = []
                for text in part.column(1).to_pylist():
                    base, every = scan(text, scope)
                    kinds = [k for _, _, k in base]
                    out.append((*(kinds.count(k) for k in BASE_KINDS), hashlib.sha256(digest(base).encode()).hexdigest(), digest(every), len(every) - len(base)))
                n1, n2, n3, sha, spans, more = map(list, zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([part.column(0), *(pa.array(n, pa.int64()) for n in (n1, n2, n3)), pa.array(sha, pa.string()), pa.array(spans, pa.string()), pa.array(more, pa.int64())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "n_linked"])

    return df.selectExpr("cast(doc_id as bigint) doc_id", "text").mapInArrow(run, SCHEMA)
