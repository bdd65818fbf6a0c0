"""Secret scans with structural confirmation.

Two layers. The base patterns report assignments, access key ids and long hex runs, leftmost and
non-overlapping per kind. On top, base64 or hex runs are decoded and reported only when their bytes
have the structure of a credential: DER whose nested lengths fit to the last byte and whose shape is
a private key, an OpenSSH key container, or a signed token whose header and claims are JSON with an
algorithm. Confirmed spans are added; base spans are never removed.

JSON or DER that is nested too deeply to be a header or a key isn't one.

Cases: null text is empty; null ids are kept; repeated rows are scanned each; empty tables give empty
results; texts of any length are scanned whole; other columns are ignored.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The three base patterns and the least lengths.
ASSIGN = re.compile(r"""(?ia:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
ASSIGN_VALUE, ACCESS_LENGTH, HEX_LENGTH = 6, 20, 24
KINDS = ("assign", "access", "hex", "pem", "token", "der")
RANK = {k: i for i, k in enumerate(KINDS)}
#: Candidates of the structural layer.
ARMOUR = re.compile(r"-----BEGIN ([A-Z0-9 ]*)PRIVATE KEY-----([A-Za-z0-9+/=\s]+)-----END \1PRIVATE KEY-----")
SIGNED = re.compile(r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]*")
RUN = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{40,}={0,2}")
#: A run as a whole, or as far as it keeps to one alphabet (a key may be followed by a mark of the other one).
ALPHABETS = (RUN, re.compile(r"[A-Za-z0-9+/]{40,}={0,2}"), re.compile(r"[A-Za-z0-9_-]{40,}={0,2}"))
HEX_RUN = re.compile(r"(?<![0-9A-Fa-f])[0-9A-Fa-f]{48,}(?![0-9A-Fa-f])")


def der_items(data: bytes, depth: int = 0) -> list | None:
    """Nested (tag, content or items) of DER that fills ``data`` exactly, or None where a length doesn't fit."""
    items, at = [], 0
    while at < len(data):
        if at + 2 > len(data):
            return None
        tag, size, at = data[at], data[at + 1], at + 2
        if size & 0x80:
            width = size & 0x7F
            if not 1 <= width <= 4 or at + width > len(data):
                return None
            size, at = int.from_bytes(data[at : at + width], "big"), at + width
        if at + size > len(data):
            return None
        content, at = data[at : at + size], at + size
        if tag & 0x20:
            if depth > 12 or (content := der_items(content, depth + 1)) is None:
                return None
        items.append((tag, content))
    return items


def is_private_key(data: bytes) -> bool:
    """Whether bytes are a private key: a DER sequence of a small version and then key parts, or an OpenSSH container."""
    if data.startswith(b"openssh-key-v1\x00"):
        at = 15
        for _ in range(3):
            if at + 4 > len(data):
                return False
            at += 4 + int.from_bytes(data[at : at + 4], "big")
        return at <= len(data)
    outer = der_items(data) if data[:1] == b"\x30" else None
    if not outer or len(outer) != 1 or outer[0][0] != 0x30 or len(outer[0][1]) < 3:
        return False
    parts = outer[0][1]
    if parts[0][0] != 0x02 or parts[0][1] not in (b"\x00", b"\x01"):
        return False
    integers = all(t == 0x02 for t, _ in parts)
    wrapped = parts[1][0] == 0x30 and parts[2][0] == 0x04
    curve = parts[1][0] == 0x04 and len(parts[1][1]) >= 16
    return (integers and len(parts) >= 6) or wrapped or curve


def unbase64(run: str) -> bytes | None:
    """Bytes of a base64 run in either alphabet, padded or not."""
    body = re.sub(r"\s+", "", run).rstrip("=").replace("-", "+").replace("_", "/")
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def is_signed_token(run: str) -> bool:
    """Whether a dotted run has a JSON header with an algorithm and JSON claims."""
    parts = []
    for piece in run.split(".")[:2]:
        data = unbase64(piece)
        try:
            parts.append(json.loads(data)) if data is not None else parts.append(None)
        except (ValueError, RecursionError):  # no JSON, or nested beyond any header
            return False
    return all(isinstance(p, dict) for p in parts) and isinstance(parts[0].get("alg"), str)


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the base patterns in code points."""
    spans = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_VALUE]
    spans += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LENGTH]
    spans += [(m.start(), m.end(), "hex") for m in HEX.finditer(text) if m.end() - m.start() >= HEX_LENGTH]
    return spans


def confirmed_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of runs whose decoded bytes are keys or signed tokens."""
    spans = []
    if "PRIVATE KEY-----" in text:
        spans += [(m.start(), m.end(), "pem") for m in ARMOUR.finditer(text) if (d := unbase64(m[2])) and is_private_key(d)]
    if "eyJ" in text:
        spans += [(m.start(), m.end(), "token") for m in SIGNED.finditer(text) if is_signed_token(m[0])]
    inside = lambda m: any(a <= m.start() and m.end() <= b for a, b, k in spans if k == "pem")
    for m in RUN.finditer(text):
        # 0x30 in front makes the first character M, whatever the length byte; OpenSSH containers begin with b3.
        if (m[0][0] == "M" or m[0][:2] == "b3") and not inside(m):
            held = (x for p in ALPHABETS if (x := p.match(m[0])) and (d := unbase64(x[0])) and is_private_key(d))
            if key := next(held, None):
                spans.append((m.start(), m.start() + key.end(), "der"))
    for m in HEX_RUN.finditer(text):
        # A DER sequence, or the first letters of an OpenSSH container.
        if m[0][:4].lower().startswith(("30", "6f70")) and len(m[0]) % 2 == 0 and is_private_key(bytes.fromhex(m[0])):
            spans.append((m.start(), m.end(), "der"))
    return spans


def scan_text(text: str) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """(base spans, all spans), each by start, then kind as listed, then end."""
    order = lambda s: (s[0], RANK[s[2]], s[1])
    base = sorted(base_spans(text), key=order)
    return base, sorted({*base, *confirmed_spans(text)}, key=order)


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, spans) with spans an array of (start, end, kind, base) for every row of ``docs``."""
    source = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    id_type = source.schema["id"].dataType.simpleString()
    span = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string()), ("base", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for text in batch.column("text"):
                base, every = scan_text(text.as_py() or "")
                known = set(base)
                rows.append([{"start": a, "end": b, "kind": k, "base": (a, b, k) in known} for a, b, k in every])
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(rows, pa.list_(span))], ["id", "spans"])

    found = source.mapInArrow(run, f"id {id_type}, spans array<struct<start:long,end:long,kind:string,base:boolean>>")
    return found.withColumnRenamed("id", id_col)


def digest(found: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """Counts per base kind, the digest of base spans, and all spans as text."""
    written = lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))
    count = lambda k: F.size(F.filter("spans", lambda s: s["base"] & (s["kind"] == k))).cast("long")
    base = F.array_join(F.transform(F.filter("spans", lambda s: s["base"]), written), ",")
    return found.select(id_col, *(count(k).alias(f"n_{k}") for k in KINDS[:3]), F.sha2(base, 256).alias("base_sha256"), F.array_join(F.transform("spans", written), ",").alias("spans"))


def brute_digest(text: str) -> tuple[int, int, int, str]:
    """Reference for tests: the base figures of one text by a plain scan from each position."""
    spans = []
    for kind, rank, pattern, group, least in (("assign", 0, ASSIGN, 2, 6), ("access", 1, ACCESS, 0, 20), ("hex", 2, HEX, 0, 24)):
        at = 0
        while at < len(text):
            if m := pattern.match(text, at):
                if len(m[group]) >= least:
                    spans.append((m.start(), rank, kind, m.end()))
                at = m.end()
            else:
                at += 1
    text_form = ",".join(f"{k}:{a}:{b}" for a, _, k, b in sorted(spans))
    return *(sum(s[2] == k for s in spans) for k in KINDS[:3]), hashlib.sha256(text_form.encode()).hexdigest()
