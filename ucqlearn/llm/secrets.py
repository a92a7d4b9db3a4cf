"""Secret scan: fixed patterns, and sliding-window entropy over candidate strings with an allow-list."""

from __future__ import annotations

import hashlib
import math
import re
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean

# fixed values: the base patterns
ASSIGN = re.compile(r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")  # maximal runs, so that no shorter one is matched inside
ASSIGN_LEAST, ACCESS_LEAST = 8, 16
KINDS = ("assign", "access", "hex", "entropy")

CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
ALLOWED = (r"[a-z]+(?:[-_/][a-z]+)*", r"[A-Z]+(?:[-_/][A-Z]+)*", r"[A-Z]?[a-z]+", r"[=_/+-]+", r"[0-9a-f]{8}-(?:[0-9a-f]{4}-){3}[0-9a-f]{12}")


@dataclass(frozen=True)
class EntropyRule:
    """``least`` bits in any window of ``window`` characters make a candidate suspicious. Classes are tried in
    order and the first that holds all its characters is used; other strings count under the last."""

    window: int = 20
    classes: tuple = (("digits", "0123456789", 2.9), ("hex", "0123456789abcdefABCDEF", 3.0), ("base32", "ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789=", 3.6), ("base36", "abcdefghijklmnopqrstuvwxyz0123456789", 3.6), ("base64", None, 3.6))
    mixed: int = 3  # kinds of characters (lower, upper, digit) that a base64 candidate must have
    allowed: tuple = field(default=ALLOWED)


def window_entropy(text: str, window: int) -> float:
    """Greatest Shannon entropy, in bits a character, of the windows of ``window`` characters (of the whole text if
    it is shorter). Counts are kept from window to window: sum n*log2(n) changes by the two characters that move."""
    size = min(window, len(text))
    if not size:
        return 0.0
    plog = [0.0] + [n * math.log2(n) for n in range(1, size + 1)]
    counts: dict[str, int] = {}
    total = 0.0
    best = 0.0
    for i, ch in enumerate(text):
        n = counts.get(ch, 0)
        total += plog[n + 1] - plog[n]
        counts[ch] = n + 1
        if i >= size:
            old = text[i - size]
            n = counts[old]
            total += plog[n - 1] - plog[n]
            counts[old] = n - 1
        if i >= size - 1:
            best = max(best, math.log2(size) - total / size)
    return best


class SecretScanner:
    def __init__(self, rule: EntropyRule = EntropyRule()):
        self.rule = rule
        self.allowed = re.compile("|".join(f"(?:{p})" for p in rule.allowed)) if rule.allowed else None
        self.sets = [(name, frozenset(chars) if chars else None, least) for name, chars, least in rule.classes]

    def base(self, text: str) -> list[tuple[int, int, int]]:
        """(start, place of the kind, end), leftmost and non-overlapping in each kind."""
        out = []
        if "=" in text or ":" in text:
            out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_LEAST]
        if "AKIA" in text:
            out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if len(m[0]) >= ACCESS_LEAST]
        out += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
        return sorted(out)

    def suspicious(self, word: str) -> bool:
        if self.allowed and self.allowed.fullmatch(word):
            return False
        chars = set(word)
        for _, own, least in self.sets:
            if own is None:
                kinds = any(c.islower() for c in chars) + any(c.isupper() for c in chars) + any(c.isdigit() for c in chars)
                return kinds >= self.rule.mixed and window_entropy(word, self.rule.window) >= least
            if chars <= own:
                return window_entropy(word, self.rule.window) >= least
        return False

    def scan(self, text: str) -> tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]:
        """Base spans, and all spans: those of suspicious candidates beside them, whether or not they overlap."""
        base = self.base(text)
        return base, sorted(base + [(m.start(), 3, m.end()) for m in CANDIDATE.finditer(text) if self.suspicious(m[0])])


def listed(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def redact(text: str, spans: list[tuple[int, int, int]], mark: str = "[REDACTED]") -> str:
    out, at = [], 0
    for s, _, e in spans:
        if e > at:
            if s >= at:
                out += [text[at:s], mark]
            at = e
    return "".join([*out, text[at:]])


FIELDS = [("n_assign", pa.int64()), ("n_access", pa.int64()), ("n_hex", pa.int64()), ("base_sha256", pa.string()), ("spans", pa.string()), ("redacted", pa.string())]


def scan_secrets(docs: DataFrame, rule: EntropyRule = EntropyRule()) -> DataFrame:
    """Every column of ``docs`` in a struct ``row``, and n_assign, n_access, n_hex, base_sha256, spans, redacted.

    Spans are in code points, end exclusive, of the whole match. ``redacted`` is the text with its spans replaced, null
    if there is none. Null and empty texts have no spans. Each row is scanned by itself, in one pass over the table.
    """
    from pyspark.sql.types import LongType, StringType, StructField, StructType

    row_type = StructType([StructField(f.name, f.dataType, True) for f in docs.schema])
    schema = StructType([StructField("row", row_type), *[StructField(n, LongType() if t == pa.int64() else StringType()) for n, t in FIELDS]])

    def run(batches):
        scanner = SecretScanner(rule)
        for batch in batches:
            out = [[] for _ in FIELDS]
            for text in batch.column(0).to_pylist():
                text = text or ""
                base, spans = scanner.scan(text)
                values = [sum(k == i for _, k, _ in base) for i in range(3)]
                values += [hashlib.sha256(listed(base).encode()).hexdigest(), listed(spans), redact(text, spans) if spans else None]
                for column, v in zip(out, values):
                    column.append(v)
            yield pa.RecordBatch.from_arrays([batch.column(1), *[pa.array(c, t) for c, (_, t) in zip(out, FIELDS)]], names=["row", *[n for n, _ in FIELDS]])

    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row")
    return docs.select(F.col("text").alias("text"), row).mapInArrow(lean(run), schema)
