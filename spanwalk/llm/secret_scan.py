"""Secret scans with structural confirmation.

Base patterns (assignments, access keys, hexadecimal runs) report spans by form alone. The
method adds spans of kinds that a form can't prove, only after decoding them:

- `jwt`: three base64url parts whose first decodes to a JSON object with an `alg` entry and
  whose second decodes to a JSON object;
- `pem`: an armoured block, with or without header lines, whose body decodes to DER with lengths
  that nest exactly, or to whole cipher blocks where its headers say that it is encrypted;
- `der`: a base64 run (on one line or wrapped) or a hexadecimal run that decodes to DER holding a
  key (PKCS#1, PKCS#8, encrypted PKCS#8, SEC1, DSA or a public key), lengths nested exactly;
- `sshkey`: an OpenSSH private or public key whose length-prefixed fields fill the blob exactly.

Defined results: null and empty texts have no spans; overlapping spans of different kinds are
all reported; very long texts are scanned whole; repeated rows give repeated results; extra
columns are not read.
"""

from __future__ import annotations

import base64
import binascii
import json
import re
import struct

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, map_texts

_ASSIGN = re.compile(r"""(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
_ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
_HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
#: A header is a JSON object, perhaps after white space.
_JWT = re.compile(r"(?<![A-Za-z0-9_-])(?:e[w-z]|[CDI][A-Za-z0-9])[A-Za-z0-9_-]{6,}\.[A-Za-z0-9_-]{4,}\.[A-Za-z0-9_-]*")
_PEM = re.compile(r"-----BEGIN ([A-Z0-9 ]{1,40})-----\s*((?:[A-Za-z][A-Za-z0-9-]{0,40}: [^\n]{0,200}\n)*)([A-Za-z0-9+/=\s]+)-----END \1-----")
_WRAPPED = re.compile(r"(?<![A-Za-z0-9+/=_-])M[A-Za-z0-9+/]{59,75}\r?\n(?:[A-Za-z0-9+/]{60,76}\r?\n)*[A-Za-z0-9+/]{1,76}={0,2}(?![A-Za-z0-9+/=])")
_RUN64 = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{40,}={0,2}")
_HEXDER = re.compile(r"(?<![0-9A-Fa-f])30[0-9A-Fa-f]{46,}")
#: Kinds in the order in which spans that start together are listed; the first three are the base.
KINDS = ("assign", "access", "hex", "jwt", "pem", "der", "sshkey")
#: Object identifiers in DER, fixed values: rsaEncryption, RSA-PSS, DSA, ecPublicKey, X25519, X448, Ed25519, Ed448; and what those of encrypted keys begin with.
_KEY_OIDS = tuple(map(bytes.fromhex, ("2a864886f70d010101", "2a864886f70d01010a", "2a8648ce380401", "2a8648ce3d0201", "2b656e", "2b656f", "2b6570", "2b6571")))
_LOCKED_OIDS = tuple(map(bytes.fromhex, ("2a864886f70d0105", "2a864886f70d010c01")))


def _unbase64(run: str) -> bytes | None:
    body = run.rstrip("=").replace("-", "+").replace("_", "/")
    if len(body) % 4 == 1:
        return None
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except binascii.Error:
        return None


def _tlv(data: bytes, at: int, end: int) -> tuple[int, int, int] | None:
    """Tag, start and end of the content of the DER value at `at`; None if its length doesn't fit."""
    if at + 2 > end:
        return None
    tag, n, at = data[at], data[at + 1], at + 2
    if n & 0x80:
        k = n & 0x7F
        if not 1 <= k <= 4 or at + k > end or data[at] == 0:
            return None
        n = int.from_bytes(data[at : at + k], "big")
        at += k
        if n < 0x80:
            return None
    return (tag, at, at + n) if at + n <= end else None


def der_children(data: bytes, start: int, end: int) -> list[tuple[int, int, int]] | None:
    """The values that fill data[start:end] exactly, or None."""
    out = []
    while start < end:
        found = _tlv(data, start, end)
        if found is None:
            return None
        out.append(found)
        start = found[2]
    return out


def der_holds_key(data: bytes) -> bool:
    """True if the bytes are one DER sequence, exactly filled, of the shape of a key."""
    top = _tlv(data, 0, len(data))
    if top is None or top[0] != 0x30 or top[2] != len(data):
        return False
    parts = der_children(data, top[1], top[2])
    if not parts:
        return False
    tags = [t for t, _, _ in parts]

    def identifier(part) -> bytes:
        inner = der_children(data, part[1], part[2]) if part[0] == 0x30 else None
        return data[inner[0][1] : inner[0][2]] if inner and inner[0][0] == 0x06 else b""

    def algorithm(part) -> bool:
        return identifier(part) in _KEY_OIDS

    if len(tags) >= 9 and set(tags[:9]) == {0x02}:  # PKCS#1: version and eight integers
        return data[parts[1][1] : parts[1][2]].lstrip(b"\0") != b"" and parts[1][2] - parts[1][1] >= 32
    if len(tags) >= 3 and tags[0] == 0x02 and algorithm(parts[1]) and tags[2] == 0x04:  # PKCS#8
        return True
    if len(tags) >= 2 and tags[:2] == [0x02, 0x04] and parts[0][2] - parts[0][1] == 1 and parts[1][2] - parts[1][1] in (20, 24, 28, 32, 48, 66):  # SEC1
        return True
    if tags == [0x30, 0x04] and identifier(parts[0]).startswith(_LOCKED_OIDS):  # encrypted PKCS#8
        return parts[1][2] - parts[1][1] >= 16
    if tags == [0x02] * 6 and parts[0][2] - parts[0][1] == 1 and parts[1][2] - parts[1][1] >= 64:  # DSA: version, p, q, g, y, x
        return True
    if tags == [0x30, 0x03] and algorithm(parts[0]):  # public key
        return True
    return tags == [0x02, 0x02] and parts[0][2] - parts[0][1] >= 64  # PKCS#1 public


def _ssh_fields(data: bytes, at: int) -> list[bytes] | None:
    out = []
    while at < len(data):
        if at + 4 > len(data):
            return None
        (n,) = struct.unpack_from(">I", data, at)
        if at + 4 + n > len(data):
            return None
        out.append(data[at + 4 : at + 4 + n])
        at += 4 + n
    return out


def ssh_holds_key(data: bytes) -> bool:
    magic = b"openssh-key-v1\0"
    if data.startswith(magic):
        at = len(magic)
        for _ in range(3):  # cipher, key derivation, its options
            if at + 4 > len(data):
                return False
            at += 4 + struct.unpack_from(">I", data, at)[0]
        if at + 4 > len(data):
            return False
        n = struct.unpack_from(">I", data, at)[0]
        fields = _ssh_fields(data, at + 4)
        return fields is not None and 1 <= n <= 16 and len(fields) == n + 1
    fields = _ssh_fields(data, 0)
    return bool(fields) and len(fields) >= 2 and re.fullmatch(rb"(ssh|ecdsa|sk)-[a-z0-9@.-]+", fields[0]) is not None


def _json_object(part: str) -> dict | None:
    raw = _unbase64(part)
    try:
        found = json.loads(raw) if raw else None
    except (ValueError, RecursionError):
        return None
    return found if isinstance(found, dict) else None


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = []
    if ":" in text or "=" in text:
        out += [("assign", m.start(), m.end()) for m in _ASSIGN.finditer(text) if m.end(1) - m.start(1) >= 6]
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in _ACCESS.finditer(text)]
    out += [("hex", m.start(), m.end()) for m in _HEX.finditer(text)]
    return out


def confirmed_spans(text: str) -> list[tuple[str, int, int]]:
    """Spans that decode to what they seem to be."""
    out = []
    if "." in text:
        for m in _JWT.finditer(text):
            head, body, _ = m.group().split(".")
            if isinstance((_json_object(head) or {}).get("alg"), str) and _json_object(body) is not None:
                out.append(("jwt", m.start(), m.end()))
    if "-----BEGIN " in text:
        for m in _PEM.finditer(text):
            raw = _unbase64("".join(m.group(3).split()))
            locked = raw and "DEK-Info: " in m.group(2) and "ENCRYPTED" in m.group(2) and len(raw) % 8 == 0
            if raw and (locked or der_holds_key(raw) or ssh_holds_key(raw)):
                out.append(("pem", m.start(), m.end()))
    armoured = [(a, b) for _, a, b in out if text.startswith("-----BEGIN", a)]
    for m in _WRAPPED.finditer(text):
        raw = _unbase64("".join(m.group().split()))
        if raw and der_holds_key(raw) and not any(a < m.start() < b for a, b in armoured):
            out.append(("der", m.start(), m.end()))
    for m in _RUN64.finditer(text):
        raw = _unbase64(m.group())
        if raw and raw[0] == 0x30 and der_holds_key(raw):
            out.append(("der", m.start(), m.end()))
        elif raw and ssh_holds_key(raw):
            out.append(("sshkey", m.start(), m.end()))
    for m in _HEXDER.finditer(text):
        run = m.group()
        if len(run) % 2 == 0 and der_holds_key(bytes.fromhex(run)):
            out.append(("der", m.start(), m.end()))
    return out


def listed(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in sorted(set(spans), key=lambda s: (s[1], KINDS.index(s[0]), s[2])))


def scan_secrets(docs: DataFrame) -> DataFrame:
    """(doc_id, base, added): spans as `kind:start:end`, in code points, end exclusive."""

    def make():
        def work(texts: list) -> dict:
            base = [base_spans(t) if t else [] for t in texts]
            added = [confirmed_spans(t) if t else [] for t in texts]
            count = lambda kind: [sum(s[0] == kind for s in b) for b in base]
            return {
                "n_assign": count("assign"), "n_access": count("access"), "n_hex": count("hex"),
                "base": [listed(b) for b in base], "spans": [listed(b + a) for b, a in zip(base, added)],
            }

        return work

    return map_texts(id_and_text(docs), make, "n_assign long, n_access long, n_hex long, base string, spans string")


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2("base", 256).alias("base_sha256"), "spans")

