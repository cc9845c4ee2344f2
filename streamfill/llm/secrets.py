"""Secret scans with linked credentials.

Three kinds of strong finding are reported wherever they stand: assignments, access identifiers, long hexadecimal
runs. Weak candidates (opaque tokens, short-named keys, endpoints) say little alone. Scopes are runs of lines without
a blank one. Identifiers, secrets and endpoints are joined with the scopes that hold them, intervals of both kinds in
order of their starts, and a weak candidate is reported only when its scope completes it: a secret needs an
identifier or an endpoint, an identifier or endpoint needs a secret. One sweep over sorted intervals does it, so the
cost follows the length of the text and the number of parts.
"""

from __future__ import annotations

import bisect
import hashlib
import itertools
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Least Shannon entropy, bits a character, of an opaque token.
ENTROPY = 3.5
KINDS = ("assign", "access", "hex", "weak_secret", "weak_id", "endpoint")


def base_findings(text: str) -> Iterator[tuple[int, int, str]]:
    """(start, end, kind) of the strong findings, per kind from the left, without overlap within a kind."""
    if ":" in text or "=" in text:
        for m in _assign().finditer(text):
            if m.end(2) - m.start(2) >= 6:
                yield m.start(), m.end(), "assign"
    if "AKIA" in text:
        for m in re.finditer("AKIA[A-Z0-9]+", text):
            if m.end() - m.start() >= 20:
                yield m.start(), m.end(), "access"
    for m in re.finditer("[0-9a-f]{24,}", text):
        yield m.start(), m.end(), "hex"


def _assign() -> re.Pattern:
    return re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)


def weak_findings(text: str) -> Iterator[tuple[int, int, str]]:
    """Candidates that are reported only when linked."""
    import math
    from collections import Counter

    if "://" in text:
        for m in re.finditer(r"(?:https?|jdbc:[a-z]+|postgres(?:ql)?|mysql|redis|mongodb|amqp|s3)://[^\s\"'<>|]{4,}", text):
            yield m.start(), m.end(), "endpoint"
    if ":" in text or "=" in text:
        for m in re.finditer(r"\b(?:user(?:name)?|login|client_?id|account|access_?(?:key_?)?id)[\"']? *[:=] *[\"']?([A-Za-z0-9_.@-]{3,})", text, re.IGNORECASE | re.ASCII):
            yield m.start(), m.end(), "weak_id"
    for m in re.finditer(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}={0,2}(?![A-Za-z0-9+/_-])", text):
        word = m.group()
        if any(c.isdigit() for c in word) and any(c.isupper() for c in word) and any(c.islower() for c in word):
            counts = Counter(word)
            if -sum(n / len(word) * math.log2(n / len(word)) for n in counts.values()) >= ENTROPY:
                yield m.start(), m.end(), "weak_secret"


ROLE = {"assign": "secret", "hex": "secret", "weak_secret": "secret", "access": "id", "weak_id": "id", "endpoint": "endpoint"}


COMPLETES = {"secret": {"id", "endpoint"}, "id": {"secret"}, "endpoint": {"secret"}}


def outside(weak: list[tuple[int, int, str]], strong: list[tuple[int, int, str]]) -> Iterator[tuple[int, int, str]]:
    """The weak candidates that overlap no strong finding of their own role: those are the same thing seen again."""
    for role in COMPLETES:
        taken = sorted((s, e) for s, e, kind in strong if ROLE[kind] == role)
        starts, furthest = [s for s, _ in taken], list(itertools.accumulate((e for _, e in taken), max))
        for s, e, kind in weak:
            if ROLE[kind] == role:
                before = bisect.bisect_left(starts, e)  # strong ones that start before this one ends
                if not before or furthest[before - 1] <= s:
                    yield s, e, kind


def linked(text: str, strong: list[tuple[int, int, str]], weak: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """The weak candidates that complementary parts of their scope complete. A part that runs over a blank line
    belongs to the scope where it starts."""
    weak = list(outside(weak, strong))
    if not weak:
        return []
    scopes = iter([*(m.start() for m in re.finditer(r"\n[ \t\r]*(?=\n)", text)), len(text) + 1])
    end, scope, roles, found = next(scopes), 0, {0: set()}, []
    for s, e, kind in sorted([*strong, *weak]):
        while s >= end:
            end, scope = next(scopes), scope + 1
        roles.setdefault(scope, set()).add(ROLE[kind])
        found.append((scope, (s, e, kind)))
    may = set(weak)
    return [part for scope, part in found if part in may and roles[scope] & COMPLETES[ROLE[part[2]]]]


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{s}:{e}" for s, e, kind in sorted(spans, key=lambda x: (x[0], KINDS.index(x[2]), x[1])))


def scan(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, n_assign, n_access, n_hex, base_sha256, spans, findings), one for each row of docs.

    findings lists structs (kind, start, end) in code points, end exclusive; spans is their text form. A null text
    counts as empty. Repeated rows are scanned each; an empty table gives an empty result; other columns are ignored.
    """

    def scanned(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            counts: list[list[int]] = [[], [], []]
            digests, spans, findings = [], [], []
            for text in batch["t"].to_pylist():
                text = text or ""
                base = list(base_findings(text))
                for column, kind in zip(counts, KINDS, strict=False):
                    column.append(sum(k == kind for _, _, k in base))
                digests.append(hashlib.sha256(joined(base).encode()).hexdigest())
                every = base + linked(text, base, list(weak_findings(text)))
                spans.append(joined(every))
                findings.append([{"kind": k, "start": s, "end": e} for s, e, k in sorted(every)])
            yield pa.RecordBatch.from_arrays(
                [batch["i"], *(pa.array(c, pa.int64()) for c in counts), pa.array(digests, pa.string()), pa.array(spans, pa.string()), pa.array(findings, span)],
                names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans", "findings"],
            )

    rows = docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t"))
    return rows.mapInArrow(scanned, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, findings array<struct<kind:string,start:long,end:long>>")
