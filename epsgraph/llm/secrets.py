"""Secret scans with multipart credential linking.

Base detectors find assignments, access identifiers and hex runs. The method looks for the parts of one credential:
identifiers (access ids, and weak ones: ``user``/``client``-style assignments), secrets (base assignments and hex runs, and
weak ones: 40-character base64-like runs of high entropy) and endpoints (URLs of API or storage hosts). Parts are joined
by interval: two complementary parts are linked when both lie in one scope (a stretch of lines without an empty line) and at
most ``reach`` code points apart. A weak part is reported only when a part of another role links to it; each candidate
takes its nearest partner of each other role (the starts of those reported are in ``linked``, nearest first), found by bisection in position
order, so no pairs are enumerated.

Spans are kind:start:end in code points, end exclusive, over the whole match, ordered by start and kind.

Defined results: a null text is empty and has no spans; repeated rows are scanned one by one; texts of any length are
scanned whole; other columns pass through and results come in one array column ``secret_spans``.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections.abc import Iterator
from itertools import accumulate
from math import log2

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import table

#: The base detectors.
ASSIGN = r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
LEAST = {"assign": 6, "access": 20, "hex": 24}
BASE = ("assign", "access", "hex")

#: Weak parts, and their place in the order of kinds.
KINDS = {k: i for i, k in enumerate((*BASE, "weak_id", "weak_secret", "endpoint"))}
WEAK_ID = r"(?:user(?:name)?|login|account|client)_?(?:id|name)?[\"']?\x20*[:=]\x20*[\"']?[A-Za-z0-9_.@-]{3,}"
WEAK_SECRET = r"(?<![A-Za-z0-9+/])[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/=])"
ENDPOINT = r"https?://[A-Za-z0-9.-]*(?:api|amazonaws|storage|vault|db)[A-Za-z0-9.-]*(?::\d+)?"
ROLES = {"assign": "secret", "hex": "secret", "weak_secret": "secret", "access": "id", "weak_id": "id", "endpoint": "endpoint"}


def entropy(s: str) -> float:
    return -sum(p * log2(p) for p in (s.count(c) / len(s) for c in set(s)))


class Scanner:
    def __init__(self, reach: int = 400, min_entropy: float = 4.0):
        self.reach, self.min_entropy = reach, min_entropy
        fold = re.ASCII | re.IGNORECASE
        self.assign = re.compile(ASSIGN, fold)
        # A shorter run fails and ends where the next could begin at the earliest, so asking for the length finds the same.
        self.access = re.compile(ACCESS[:-1] + "{%d,}" % (LEAST["access"] - 4))
        self.hex = re.compile(HEX[:-1] + "{%d,}" % LEAST["hex"])
        self.weak_id, self.weak_secret, self.endpoint = re.compile(WEAK_ID, fold), re.compile(WEAK_SECRET), re.compile(ENDPOINT, fold)

    def base(self, text: str) -> list[tuple[str, int, int]]:
        low = text.lower()
        out = []
        if "pass" in low or "secret" in low or "token" in low or "api" in low:
            out += [("assign", *m.span()) for m in self.assign.finditer(text) if len(m[2]) >= LEAST["assign"]]
        if "AKIA" in text:
            out += [("access", *m.span()) for m in self.access.finditer(text)]
        return out + [("hex", *m.span()) for m in self.hex.finditer(text)]

    def weak(self, text: str, low: str) -> list[tuple[str, int, int]]:
        out = []
        if "user" in low or "login" in low or "account" in low or "client" in low:
            out += [("weak_id", *m.span()) for m in self.weak_id.finditer(text)]
        if "http" in low:
            out += [("endpoint", *m.span()) for m in self.endpoint.finditer(text)]
        return out

    def weak_secrets(self, text: str) -> list[tuple[str, int, int]]:
        return [("weak_secret", *m.span()) for m in self.weak_secret.finditer(text) if entropy(m[0]) >= self.min_entropy]

    def link(self, text: str, parts: list[tuple[str, int, int]]) -> dict[int, list[int]]:
        """Positions of the nearest part of each other role in the same scope, nearest first, by position of the part."""
        found: dict[int, list[int]] = {}
        by_role: dict[str, list[int]] = {}
        for i, (kind, _, _) in enumerate(parts):
            by_role.setdefault(ROLES[kind], []).append(i)
        starts = {r: [parts[i][1] for i in at] for r, at in by_role.items()}
        # Of the parts that start before, the nearest ends last; parts of a role may lie in one another.
        last = {r: list(accumulate(at, lambda i, j: j if parts[j][2] >= parts[i][2] else i)) for r, at in by_role.items()}
        for i, (kind, start, end) in enumerate(parts):
            near = []
            for role, at in by_role.items():
                if role == ROLES[kind]:
                    continue
                j = bisect_left(starts[role], start)
                tries = []
                for k in (last[role][j - 1 : j] if j else []) + at[j : j + 1]:
                    _, s, e = parts[k]
                    gap = max(s - end, start - e, 0)
                    if gap <= self.reach and not self._parted(text, min(end, e), max(start, s)):
                        tries.append((gap, k))
                near += [min(tries)] if tries else []
            if near:
                found[i] = [k for _, k in sorted(near)]
        return found

    @staticmethod
    def _parted(text: str, lo: int, hi: int) -> bool:
        return "\n\n" in text[lo:hi]

    def spans(self, text: str) -> list[tuple[str, int, int, list[int]]]:
        """(kind, start, end, starts of the linked parts, nearest first) of what is reported."""
        base = self.base(text)
        weak = self.weak(text, text.lower())
        # Weak secrets count only beside an identifier or an endpoint.
        if weak or any(k == "access" for k, _, _ in base):
            taken = {(s, e) for _, s, e in base}
            weak += [p for p in self.weak_secrets(text) if p[1:] not in taken and not any(s <= p[1] and p[2] <= e for s, e in taken)]
        parts = sorted(base + weak, key=lambda p: (p[1], KINDS[p[0]]))
        links = self.link(text, parts) if len(parts) > 1 else {}
        # An endpoint and a weak id confirm each other only through a secret, so a weak part needs a secret among its partners or to be one.
        keep = lambda i: parts[i][0] in BASE or i in links and "secret" in (ROLES[parts[k][0]] for k in (i, *links[i]))
        kept = {i for i in range(len(parts)) if keep(i)}
        return [(*parts[i], [parts[k][1] for k in links.get(i, []) if k in kept]) for i in sorted(kept)]


SPANS = "array<struct<kind: string, start: bigint, end: bigint, linked: array<bigint>>>"


def scan_secrets(docs: DataFrame, reach: int = 400) -> DataFrame:
    """``docs`` with ``secret_spans``."""
    schema = T.StructType([f for f in docs.schema.fields if f.name != "secret_spans"]).add("secret_spans", T._parse_datatype_string(SPANS))
    docs = docs.select(*[f.name for f in schema.fields[:-1]])
    at = docs.columns.index("text")
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("linked", pa.list_(pa.int64()))]))

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(reach)
        for b in batches:
            found = [[dict(zip(("kind", "start", "end", "linked"), s)) for s in scanner.spans(t.as_py() or "")] for t in b.column(at)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(found, kind)], names=[*b.schema.names, "secret_spans"])

    return docs.mapInArrow(scan, schema)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_secrets(table(spark, sf_dir, "documents", "doc_id", "text")).drop("text")
    spans = F.col("secret_spans")
    base = F.filter(spans, lambda s: s["kind"].isin(*BASE))
    count = lambda k: F.size(F.filter(spans, lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    joined = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    return found.select("doc_id", *[count(k) for k in BASE], F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined(spans).alias("spans"))
