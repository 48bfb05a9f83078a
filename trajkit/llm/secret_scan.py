r"""Secret scanning with structural confirmation.

Plain patterns find assignments, access keys and long hex runs. Beyond them, base64 and hex
candidates are decoded and their structure is parsed before anything is reported: nested
tag-length-value key encodings, length-prefixed key blobs, and the headers of signed tokens.
"""

from __future__ import annotations

import base64
import binascii
import bisect
import hashlib
import json
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from trajkit.llm.common import pieces

#: The base patterns and least lengths of the scan.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "der", "blob", "signed")
#: Candidates for decoding.
_SIGNED = re.compile(r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]*")
_BASE64 = re.compile(r"[A-Za-z0-9+/]{40}[A-Za-z0-9+/\r\n]*={0,2}")
_HEX_ANY = re.compile(r"[0-9a-fA-F]{64,}")
_HAS_ASSIGN = re.compile(r"[:=]")


def tlv_depth(data: bytes) -> int:
    """How deep well-formed tag-length-value nesting goes, in one pass at any depth; 0 if lengths don't add up to the whole."""
    at, best, ends = 0, 0, [len(data)]
    while ends:
        if at == ends[-1]:
            ends.pop()
            continue
        if at + 2 > ends[-1]:
            return 0
        tag, size = data[at], data[at + 1]
        at += 2
        if size & 0x80:
            n = size & 0x7F
            if not 1 <= n <= 4 or at + n > ends[-1]:
                return 0
            size = int.from_bytes(data[at : at + n], "big")
            at += n
        if at + size > ends[-1]:
            return 0
        best = max(best, len(ends))
        if tag & 0x20:
            ends.append(at + size)
        else:
            at += size
    return best


def is_key_encoding(data: bytes) -> bool:
    """A sequence that spans the whole (but for a few padding bytes), nested, with at least one integer or object id."""
    if len(data) < 24 or data[0] != 0x30:
        return False
    head, n = 2, data[1]
    if n & 0x80:
        k = n & 0x7F
        if not 1 <= k <= 4 or len(data) < 2 + k:
            return False
        n, head = int.from_bytes(data[2 : 2 + k], "big"), 2 + k
    if n < 16 or not 0 <= len(data) - head - n <= 3:
        return False
    return tlv_depth(data[: head + n]) >= 2 and data[head] in (0x02, 0x30, 0x06)


def is_length_prefixed(data: bytes) -> bool:
    """A private key container's magic, or a run of length-prefixed fields that starts with an algorithm name and fills the whole."""
    if data.startswith(b"openssh-key-v1\x00"):
        return True
    at, fields = 0, 0
    while at + 4 <= len(data):
        n = int.from_bytes(data[at : at + 4], "big")
        if n > len(data) - at - 4:
            return False
        if fields == 0 and not re.fullmatch(rb"(ssh|ecdsa|sk)-[a-z0-9@.-]{3,40}", data[4 : 4 + n]):
            return False
        at, fields = at + 4 + n, fields + 1
    return fields >= 2 and at == len(data)


def decode_base64(text: str) -> bytes:
    clean = re.sub(r"[\r\n=]", "", text).replace("-", "+").replace("_", "/")
    try:
        return base64.b64decode(clean[: len(clean) // 4 * 4] if len(clean) % 4 == 1 else clean + "=" * (-len(clean) % 4))
    except (binascii.Error, ValueError):
        return b""


def is_signed_header(text: str) -> bool:
    """The first part of a signed token: base64 of a JSON object that names an algorithm."""
    try:
        found = json.loads(decode_base64(text))
    except (ValueError, RecursionError):
        return False
    return isinstance(found, dict) and isinstance(found.get("alg"), str)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    found = []
    if _HAS_ASSIGN.search(text):
        found += [("assign", *m.span()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        found += [("access", *m.span()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    return found + [("hex", *m.span()) for m in HEX.finditer(text)]


def kind_of(data: bytes) -> str:
    return "der" if is_key_encoding(data) else "blob" if is_length_prefixed(data) else ""


def inner_ends(run: str) -> list[int]:
    """Where else a base64 run over several lines may end: its first line, and the line at which its key encoding is full."""
    breaks = [m.start() for m in re.finditer(r"[\r\n]+", run)]
    if not breaks:
        return []
    head = decode_base64(run[:12].replace("\n", "").replace("\r", ""))
    ends = breaks[:1]
    if head[:1] == b"\x30" and len(head) >= 6:
        k = head[1] & 0x7F if head[1] & 0x80 else 0
        if k <= 4:
            total = (int.from_bytes(head[2 : 2 + k], "big") if k else head[1]) + 2 + k
            chars, at = 0, 0
            for end in breaks:
                chars, at = chars + len(run[at:end].strip("\r\n=")), end
                if chars * 3 // 4 >= total:
                    return [*ends, end] if end != breaks[0] else ends
    return ends


def confirmed_spans(text: str) -> list[tuple[str, int, int]]:
    """Spans that are reported only because what they decode to parses."""
    found = []
    if "eyJ" in text:
        found += [("signed", *m.span()) for m in _SIGNED.finditer(text) if is_signed_header(m[0].split(".")[0])]
    starts, ends = [a for _, a, _ in found], [b for _, _, b in found]  # ascending, and they don't overlap
    for pattern, decode in ((_BASE64, decode_base64), (_HEX_ANY, lambda x: bytes.fromhex(x[: len(x) // 2 * 2]))):
        for m in pattern.finditer(text):
            k = bisect.bisect_left(starts, m.end())
            if k and ends[k - 1] > m.start():
                continue
            # A line of text after the run may read like more of it.
            for run in (m[0], *(m[0][:e] for e in (inner_ends(m[0]) if pattern is _BASE64 else []))):
                if kind := kind_of(decode(run)):
                    found.append((kind, m.start(), m.start() + len(run.rstrip("\r\n"))))
                    break
    return found


def in_order(spans: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    return sorted(spans, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def joined(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in in_order(spans))


def redact(text: str, spans: list[tuple[str, int, int]], mark: str = "[secret]") -> str:
    out, at = [], 0
    for _, a, b in in_order(spans):
        if b <= at:
            continue
        if a >= at:
            out += [text[at:a], mark]
        at = b
    return "".join([*out, text[at:]])


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans for every row; offsets are code points, ends exclusive.

    Null text: empty (no spans; the digest of the empty string). Repeated rows give repeated results. Null doc_id stays null.
    Empty table: no rows. Other columns are ignored. Whole texts are scanned.
    """

    def run(batches):
        for b in pieces(batches):
            rows = []
            for x in b.column(1):
                text = x.as_py() or ""
                base = base_spans(text)
                kinds = [s[0] for s in base]
                rows.append((*(kinds.count(k) for k in KINDS[:3]), hashlib.sha256(joined(base).encode()).hexdigest(), joined(base + confirmed_spans(text))))
            cols = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c, pa.int64()) for c in cols[:3]), *(pa.array(c, pa.string()) for c in cols[3:])], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redacted(docs: DataFrame, mark: str = "[secret]") -> DataFrame:
    """The same rows and columns with every span of ``text`` replaced by ``mark``; n_chars, where there is one, follows."""
    names, kinds = docs.columns, docs.schema
    place = names.index("text")

    def run(batches):
        for b in pieces(batches):
            texts = [None if (t := x.as_py()) is None else redact(t, base_spans(t) + confirmed_spans(t), mark) for x in b.column(place)]
            cols = [pa.array(texts, pa.string()) if k == place else b.column(k) for k in range(len(names))]
            yield pa.RecordBatch.from_arrays(cols, names)

    out = docs.mapInArrow(run, kinds)
    if "n_chars" in names:
        from pyspark.sql import functions as F

        out = out.withColumn("n_chars", F.length("text").cast(kinds["n_chars"].dataType)).select(*names)
    return out
