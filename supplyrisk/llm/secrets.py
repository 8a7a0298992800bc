"""Secret scan: pattern hits, then spans confirmed by their decoded structure.

Base kinds are the plain patterns (`assign`, `access`, `hex`). The structural pass
decodes base64 and hex candidates and adds a span only where the bytes parse:

* `pem`  a PEM block of a private key whose body decodes to a key encoding; an encrypted
  one must be the ASN.1 of an encrypted key, or name its cipher and IV and fill whole blocks,
* `der`  a bare base64 or hex run (either case) that is a PKCS#1, PKCS#8 or EC private key
  (every nested ASN.1 length must fit exactly), or an OpenSSH private key; and a base64 run
  that decodes to the base64 or the PEM block of one, NEST levels deep at most,
* `jwt`  a signed token: header JSON names a known algorithm, the payload is JSON and
  the signature has the length of that algorithm.

Null text counts as empty. Offsets are code points of the whole text, end exclusive.
"""

from __future__ import annotations

import base64
import binascii
import bisect
import json
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The patterns of the base kinds, in the order kinds are listed.
ASSIGN = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{12,}")
HEX = re.compile(r"[0-9a-f]{32,}")
HEX_KEY = re.compile(r"(?<![0-9A-Fa-f])(?:30|6[Ff]70656[Ee]737368)[0-9A-Fa-f]{62,}(?![0-9A-Fa-f])")
KINDS = ("assign", "access", "hex", "pem", "der", "jwt")
BASE_KINDS = KINDS[:3]

ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
# A DER sequence starts with 0x30, base64 "M"; the OpenSSH magic with "b3Bl".
BASE64_KEY = re.compile(r"(?<![A-Za-z0-9])(?=(?:M|b3Bl)[A-Za-z0-9+/_-]{14})")
BASE64_PART = re.compile(r"[A-Za-z0-9+/_-]+")
BASE64_LINE = re.compile(r"\r?\n[ \t]*([A-Za-z0-9+/_-]+)(={0,2})(?=[ \t]*(?:\r?\n|$))")
OPENSSH_LINE = 200
# Base64 of what base64 of keys begins with (0x30, the OpenSSH magic) and of a PEM line, once or twice.
NESTED = re.compile(r"(?<![A-Za-z0-9+/_-])(?:TU|VFV|YjNCbGJ|WWpOQ|LS0tLS1C|TFMwdExTM)[A-Za-z0-9+/_-]{40,}={0,2}")
NEST = 2
DEK_INFO = re.compile(r"DEK-Info: *[A-Z0-9-]+, *([0-9A-Fa-f]{16}|[0-9A-Fa-f]{32})\s")
PEM_END = re.compile(r"-----END ((?:[A-Z0-9]+ )*PRIVATE KEY)-----")
NEXT_LINE = re.compile(r"\r?\n[ \t]*")
JWT = re.compile(r"(?<![A-Za-z0-9_-])(eyJ[A-Za-z0-9_-]{8,})\.([A-Za-z0-9_-]{2,})\.([A-Za-z0-9_-]{16,})(?![A-Za-z0-9_-])")
PEM_BEGIN = re.compile(r"-----BEGIN ((?:[A-Z0-9]+ )*PRIVATE KEY)-----")
SIGNATURE_BYTES = {"HS256": (32,), "HS384": (48,), "HS512": (64,), "ES256": (64,), "ES384": (96,), "ES512": (132,), "EdDSA": (64, 114), "RS256": (), "RS384": (), "RS512": (), "PS256": (), "PS384": (), "PS512": ()}

SPAN_TYPE = "array<struct<kind:string,start:long,end:long>>"


def _der_items(data: bytes) -> list[tuple[int, bytes]] | None:
    """Tag and content of each element; None unless the lengths fill data exactly."""
    out, at = [], 0
    while at < len(data):
        if at + 2 > len(data):
            return None
        tag, size, at = data[at], data[at + 1], at + 2
        if size & 0x80:
            n = size & 0x7F
            if not 1 <= n <= 4 or at + n > len(data):
                return None
            size, at = int.from_bytes(data[at : at + n], "big"), at + n
        if at + size > len(data):
            return None
        out.append((tag, data[at : at + size]))
        at += size
    return out


def is_private_der(data: bytes) -> bool:
    top = _der_items(data)
    if not top or len(top) != 1 or top[0][0] != 0x30:
        return False
    parts = _der_items(top[0][1])
    if not parts or len(parts) < 2 or parts[0][0] != 0x02 or len(parts[0][1]) != 1:
        return False
    tags = [t for t, _ in parts]
    if len(parts) >= 9 and all(t == 0x02 for t in tags[:9]):  # PKCS#1
        return len(parts[1][1]) >= 32
    if len(parts) >= 3 and tags[1] == 0x30 and tags[2] == 0x04:  # PKCS#8
        algorithm = _der_items(parts[1][1])
        return bool(algorithm) and algorithm[0][0] == 0x06 and len(parts[2][1]) >= 16
    return tags[1] == 0x04 and parts[0][1] == b"\x01" and len(parts[1][1]) >= 16  # SEC 1


def is_openssh(data: bytes) -> bool:
    """The magic, then cipher, kdf and options as length-prefixed strings, then a count."""
    magic = b"openssh-key-v1\0"
    if not data.startswith(magic):
        return False
    at = len(magic)
    for _ in range(3):
        if at + 4 > len(data):
            return False
        at += 4 + int.from_bytes(data[at : at + 4], "big")
    return at + 4 <= len(data) and 1 <= int.from_bytes(data[at : at + 4], "big") <= 16


def _decoded(run: str) -> bytes | None:
    run = run.rstrip("=").replace("-", "+").replace("_", "/")
    if len(run) % 4 == 1:
        return None
    try:
        return base64.b64decode(run + "=" * (-len(run) % 4), validate=True)
    except (ValueError, binascii.Error):
        return None


def is_encrypted_der(data: bytes | None) -> bool:
    """A sequence of an algorithm (with its identifier) and the encrypted bytes, in whole blocks."""
    top = _der_items(data) if data else None
    parts = _der_items(top[0][1]) if top and len(top) == 1 and top[0][0] == 0x30 else None
    if not parts or [t for t, _ in parts] != [0x30, 0x04]:
        return False
    algorithm = _der_items(parts[0][1])
    return bool(algorithm) and algorithm[0][0] == 0x06 and len(parts[1][1]) >= 48 and len(parts[1][1]) % 8 == 0


def is_encrypted_body(head: str, data: bytes | None) -> bool:
    """Headers of an encrypted block with an IV, and a body of whole blocks of that size."""
    iv = DEK_INFO.search(head)
    return bool(iv and "Proc-Type: 4,ENCRYPTED" in head and data and len(data) >= 48 and len(data) % (len(iv[1]) // 2) == 0)


def _pem_spans(text: str) -> list[tuple[str, int, int]]:
    """Confirmed blocks; each BEGIN goes with the next END of its kind, found in one pass."""
    ends: dict[str, list[int]] = {}
    for m in PEM_END.finditer(text):
        ends.setdefault(m[1], []).append(m.start())
    out, past = [], 0
    begins = list(PEM_BEGIN.finditer(text))
    for i, m in enumerate(begins):
        here = ends.get(m[1], [])
        k = bisect.bisect_left(here, m.end())
        if m.start() < past or k == len(here):
            continue
        end = here[k]
        # Of BEGINs of one kind before the same END the last one is its own.
        if i + 1 < len(begins) and begins[i + 1][1] == m[1] and begins[i + 1].start() < end:
            continue
        lines = text[m.end() : end].splitlines()
        head = "".join(f"{x}\n" for x in lines if ":" in x)
        data = _decoded("".join("".join(x for x in lines if ":" not in x).split()))
        if _is_key(data) or (is_encrypted_der(data) if m[1].startswith("ENCRYPTED") else is_encrypted_body(head, data)):
            past = end + len(f"-----END {m[1]}-----")
            out.append(("pem", m.start(), past))
    return out


def _holds_key(run: str, depth: int = NEST) -> bool:
    """Whether a base64 run decodes to text that is the base64 or the PEM block of a key."""
    data = _decoded(run)
    try:
        inner = data.decode("ascii").strip() if data else ""
    except UnicodeDecodeError:
        return False
    if not inner:
        return False
    if "-----BEGIN " in inner:
        return bool(_pem_spans(inner))
    inner = "".join(inner.split())
    if not re.fullmatch(r"[A-Za-z0-9+/_-]+={0,2}", inner):
        return False
    return _is_key(_decoded(inner)) or depth > 1 and _holds_key(inner, depth - 1)


def _is_key(data: bytes | None) -> bool:
    return bool(data) and (is_private_der(data) or is_openssh(data))


def is_signed_token(header: str, payload: str, signature: str) -> bool:
    try:
        head, body = json.loads(_decoded(header) or b"null"), json.loads(_decoded(payload) or b"null")
    except (ValueError, UnicodeDecodeError, RecursionError):
        return False
    if not isinstance(head, dict) or not isinstance(body, dict) or head.get("alg") not in SIGNATURE_BYTES:
        return False
    lengths, signed = SIGNATURE_BYTES[head["alg"]], _decoded(signature)
    return signed is not None and (len(signed) in lengths if lengths else len(signed) >= 128)


def _padded(text: str, at: int) -> int:
    for _ in range(2):
        at += text.startswith("=", at)
    return at


def base64_key(text: str, start: int) -> tuple[int, bool] | None:
    """End of the private key whose base64 begins at start, and whether it is wrapped over lines."""
    if text.startswith("b3Bl", start):
        run = BASE64_PART.match(text, start)
        end, lines = run.end(), [run[0]]
        # No whole key fits a line of OPENSSH_LINE characters, so a shorter run is wrapped or cut.
        while len(run[0]) <= OPENSSH_LINE and (m := BASE64_LINE.match(text, end)):
            lines.append(m[1])
            end = m.end(2)
            if m[2] or len(m[1]) < len(lines[0]):
                break
        return (_padded(text, end), len(lines) > 1) if is_openssh(_decoded("".join(lines)) or b"") else None
    head = _decoded(text[start : start + 8])
    if not head or head[0] != 0x30:
        return None
    n = head[1] & 0x7F if head[1] & 0x80 else 0
    size = 2 + n + (int.from_bytes(head[2 : 2 + n], "big") if n else head[1])
    need = (size * 8 + 5) // 6  # characters without padding
    if n > 4 or need > len(text) - start:
        return None
    run = BASE64_PART.match(text, start, start + need + 1)  # no further than the key could be
    end, lines = run.end(), [run[0]]
    if need < len(run[0]):
        return None
    have = len(run[0])
    while have < need and (m := NEXT_LINE.match(text, end)) and (run := BASE64_PART.match(text, m.end())):
        lines.append(run[0])
        have, end = have + len(run[0]), run.end()
    return (_padded(text, end), len(lines) > 1) if have == need and is_private_der(_decoded("".join(lines)) or b"") else None


def find_spans(text: str | None) -> list[tuple[str, int, int]]:
    """All spans of one text by start, then kind as listed in KINDS."""
    if not text:
        return []
    found: list[tuple[str, int, int]] = []
    low = text.lower()
    if any(w in low for w in ASSIGN_WORDS):
        found += [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if len(m[1]) >= 8]
    if "AKIA" in text:
        found += [("access", m.start(), m.end()) for m in ACCESS.finditer(text)]
    for m in HEX.finditer(text):
        found.append(("hex", m.start(), m.end()))
        run = m[0]
        if run.startswith(("30", "6f70656e737368")) and len(run) % 2 == 0 and _is_key(bytes.fromhex(run)):
            found.append(("der", m.start(), m.end()))
    if "3" in text:
        for m in HEX_KEY.finditer(text):
            if len(m[0]) % 2 == 0 and not m[0].islower() and not m[0].isdigit() and _is_key(bytes.fromhex(m[0])):
                found.append(("der", m.start(), m.end()))
    if "-----BEGIN " in text:
        found += _pem_spans(text)
    for m in NESTED.finditer(text):
        if _holds_key(m[0]):
            found.append(("der", m.start(), m.end()))
    armoured = [(x, y) for kind, x, y in found if kind == "pem"]  # in order, apart
    past = 0
    for m in BASE64_KEY.finditer(text):
        if m.start() < past or not (got := base64_key(text, m.start())):
            continue
        k = bisect.bisect_right(armoured, (m.start(), len(text))) - 1
        if got[1] and k >= 0 and m.start() < armoured[k][1]:
            continue
        past = got[0]
        found.append(("der", m.start(), past))
    if "eyJ" in text:
        found += [("jwt", m.start(), m.end()) for m in JWT.finditer(text) if is_signed_token(m[1], m[2], m[3])]
    found.sort(key=lambda s: (s[1], KINDS.index(s[0]), s[2]))
    return found


def scan_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: the id and its spans (kind, start, end), maybe none.

    Nulls: a null id is passed on, a null text has no spans. Repeated rows give
    repeated results; other columns are not read. No shuffle, one batch in memory."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        span = pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])
        for batch in batches:
            spans = [[{"kind": k, "start": s, "end": e} for k, s, e in find_spans(x.as_py())] for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(spans, pa.list_(span))], names=["doc_id", "spans"])

    picked = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return picked.mapInArrow(scan, f"doc_id long, spans {SPAN_TYPE}")


def joined_spans(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
