"""Secret scanning with structural confirmation of encoded candidates."""

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

_ASCII_I = re.IGNORECASE | re.ASCII
_ASSIGN = re.compile(r"(?:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", _ASCII_I)
_ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
_HEX = re.compile(r"[0-9a-f]{24,}")
_TOKEN = re.compile(r"(?<![A-Za-z0-9_.-])(eyJ[A-Za-z0-9_-]+)\.([A-Za-z0-9_-]+)\.([A-Za-z0-9_-]*)", re.ASCII)
_ARMOUR = re.compile(r"-----BEGIN ([A-Z0-9 ]*)-----((?:(?!-----).)*)-----END \1-----", re.ASCII | re.DOTALL)
_ESCAPED = re.compile(r"\\+[rn]")
#: First line of what may be a key in base64, and a further line of it; ends of lines may be written as escapes.
_HEAD = re.compile(r"(?:(?<=\\n)|(?<=\\r)|(?<![A-Za-z0-9+/_-]))(?:M|AAAA|b3Bl)[A-Za-z0-9+/_-]{15,}={0,2}", re.ASCII)
_NEXT = re.compile(r"(?:[ \t]*(?:\r\n|\r|\n)[ \t]*|(?:\\+r)?\\+n|\\+r)([A-Za-z0-9+/_-]+={0,2})", re.ASCII)
_PACKED = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{40,}={0,2}", re.ASCII)
_LONG_HEX = re.compile(r"(?<![0-9A-Fa-f])(?:[0-9A-Fa-f]{2}){32,}(?![0-9A-Fa-f])")

#: Kinds in the order in which spans that start together are listed.
KINDS = ("assign", "access", "hex", "signed", "der", "sshkey")


def _unpack(text: str) -> bytes | None:
    body = text.rstrip("=").replace("-", "+").replace("_", "/")
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _element(data: bytes, at: int, end: int) -> tuple[int, int, int] | None:
    """Tag, first content byte and end of the DER element at `at`, if it fits before `end`."""
    if at + 2 > end:
        return None
    tag, size, begin = data[at], data[at + 1], at + 2
    if size & 0x80:
        n = size & 0x7F
        if not 1 <= n <= 4 or begin + n > end or data[begin] == 0:
            return None
        size, begin = int.from_bytes(data[begin : begin + n], "big"), begin + n
        if size < 0x80:
            return None
    return (tag, begin, begin + size) if begin + size <= end else None


def is_der_key(data: bytes) -> bool:
    """Whether `data` is one SEQUENCE whose elements fill it exactly and start as keys do.

    Accepted: a version INTEGER 0 to 3 and then a long INTEGER, an OCTET STRING or an
    algorithm SEQUENCE with an object identifier; or such a SEQUENCE and a BIT STRING.
    """
    top = _element(data, 0, len(data))
    if not top or top[0] != 0x30 or top[2] != len(data):
        return False
    parts, at = [], top[1]
    while at < top[2]:
        part = _element(data, at, top[2])
        if not part:
            return False
        parts.append(part)
        at = part[2]
    if len(parts) < 2:
        return False

    def names(part: tuple[int, int, int]) -> bool:
        inner = _element(data, part[1], part[2]) if part[0] == 0x30 else None
        return bool(inner) and inner[0] == 0x06

    (tag, begin, end), second = parts[0], parts[1]
    if tag == 0x02 and end - begin == 1 and data[begin] <= 3:
        return names(second) or second[0] == 0x04 or (second[0] == 0x02 and second[2] - second[1] >= 16 and len(parts) >= 6)
    return names(parts[0]) and second[0] == 0x03


def is_ssh_key(data: bytes) -> bool:
    """Whether `data` is the modern private-key container, or length-prefixed fields led by a key type."""
    magic = b"openssh-key-v1\x00"
    at = len(magic) if data.startswith(magic) else 0
    fields = 0
    while at + 4 <= len(data):
        size = int.from_bytes(data[at : at + 4], "big")
        if at + 4 + size > len(data):
            return False
        if not fields and not at and not re.match(rb"(ssh-|ecdsa-sha2-|sk-)", data[4 : 4 + size]):
            return False
        at, fields = at + 4 + size, fields + 1
        if fields == 3 and data.startswith(magic):
            return True
    return at == len(data) and fields >= 2


def is_signed_header(part: str) -> bool:
    """Whether a token's first part is a JSON object that names its algorithm."""
    data = _unpack(part)
    try:
        found = json.loads(data.decode("utf-8")) if data else None
    except (UnicodeDecodeError, ValueError, RecursionError):
        return False
    return isinstance(found, dict) and isinstance(found.get("alg"), str)


def _structure(data: bytes | None) -> str | None:
    if not data:
        return None
    return "der" if is_der_key(data) else "sshkey" if is_ssh_key(data) else None


def _armoured(body: str) -> bytes | None:
    """Bytes between armour lines: ends of lines may be escapes; header lines (`name: value`) and their continuations are passed."""
    kept, header = [], None
    for line in _ESCAPED.sub("\n", body).splitlines():
        indent = len(line) - len(line.lstrip())
        if ":" in line or (header is not None and line.strip() and (header[1] or indent > header[0])):
            header = (header[0] if header and ":" not in line else indent, line.rstrip().endswith("\\"))
            continue
        header = None
        kept += line.split()
    return _unpack("".join(kept))


def _wrapped(text: str, head: re.Match) -> tuple[int, str] | None:
    """End and kind of the key that begins with the line `head`, in as many lines as its structure takes."""
    first = _unpack(head[0].rstrip("=")[:16]) or b""
    need = 0
    if first[:1] == b"\x30":  # the DER header tells how many characters follow
        n = first[1] & 0x7F if first[1] & 0x80 else 0
        size = int.from_bytes(first[2 : 2 + n], "big") if n else first[1]
        need = -(-(2 + n + size) * 8 // 6) if n <= 4 else 0
    if not need and not re.match(rb"\x00\x00\x00.(ssh|ecd|sk-)|openssh-key", first, re.DOTALL):
        return None
    lines, end, held = [head[0]], head.end(), len(head[0].rstrip("="))
    while True:
        if held >= need >= 40 or not need:
            if held == need or not need:
                if kind := _structure(_unpack("".join(lines))):
                    return end, kind
            if need:
                return None
        more = None if lines[-1].endswith("=") else _NEXT.match(text, end)
        if not more or (need and need < 40):
            return None
        lines.append(more[1])
        end, held = more.end(), held + len(more[1].rstrip("="))


def scan_text(text: str) -> list[tuple[int, int, str]]:
    """All spans (start, end, kind) of one text, by start and then kind. Offsets count code points."""
    found = [(m.start(), m.end(), "assign") for m in _ASSIGN.finditer(text) if len(m[1]) >= 6]
    found += [(m.start(), m.end(), "access") for m in _ACCESS.finditer(text)]
    found += [(m.start(), m.end(), "hex") for m in _HEX.finditer(text)]
    for m in _TOKEN.finditer(text):
        if is_signed_header(m[1]):
            found.append((m.start(), m.end(), "signed"))
    for m in _ARMOUR.finditer(text):
        if kind := _structure(_armoured(m[2])):
            found.append((m.start(), m.end(), kind))
    for pattern, decode in ((_PACKED, _unpack), (_LONG_HEX, bytes.fromhex)):
        for m in pattern.finditer(text):
            if (kind := _structure(decode(m[0]))) and not any(a <= m.start() and m.end() <= b and k == kind for a, b, k in found):
                found.append((m.start(), m.end(), kind))
    for m in _HEAD.finditer(text):
        if (hit := _wrapped(text, m)) and not any(a <= m.start() and hit[0] <= b and k == hit[1] for a, b, k in found):
            found.append((m.start(), *hit))
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def _joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def scan_secrets(docs: DataFrame) -> DataFrame:
    """Scan every whole text: doc_id, n_assign, n_access, n_hex, base_sha256, spans.

    Base kinds are plain patterns. Structural kinds are reported only once their bytes are
    decoded and parsed: `signed` (a token whose header names an algorithm), `der` (nested
    lengths that fill the value exactly and start as a key) and `sshkey` (length-prefixed
    fields). Null and empty texts give no spans; rows stay one to one, repeated rows
    and null ids included; other columns are not read. No shuffle, one pass.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            spans = [scan_text(t or "") for t in batch.column("text").to_pylist()]
            base = [[s for s in x if s[2] in KINDS[:3]] for x in spans]
            counts = [pa.array([sum(s[2] == k for s in x) for x in base], pa.int64()) for k in KINDS[:3]]
            digests = [hashlib.sha256(_joined(x).encode()).hexdigest() for x in base]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), *counts, pa.array(digests, pa.string()), pa.array([_joined(x) for x in spans], pa.string())],
                ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(
        run, f"doc_id {kind}, n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string"
    )
