"""Secret scans with structural confirmation.

Three base patterns report what they match. Runs that may hold encoded keys are
decoded and must parse before they are reported as well:

* ``pem``: a private-key block whose body decodes to DER, to the binary form
  of OpenSSH keys, or, under an encryption header, to whole cipher blocks;
* ``der``: base64 or hex that decodes to a private-key structure: one outer
  sequence whose nested lengths fill it exactly, with a version or the scheme it
  is encrypted by first;
* ``ssh``: base64 or hex that decodes to the OpenSSH private-key form, whose
  length-prefixed strings stay inside the data;
* ``jwt``: a signed token: three parts, of which the first decodes to a JSON
  object with ``alg`` and the second to a JSON object.

Structures may start anywhere in a run, whose lines may be wrapped: the lines are
joined, and a structure takes as many characters as its own lengths say.

Positions are code points, ends exclusive. A null or empty text has no spans;
repeated rows are scanned each for themselves; texts of any length are scanned
whole; an empty table gives no rows. ``scan`` reads no other columns; ``redact``
keeps them as they are, whatever their names.
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

from .workers import lean

KINDS = ("assign", "access", "hex", "pem", "der", "ssh", "jwt")
_RANK = {k: i for i, k in enumerate(KINDS)}


def _either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


# Each alternative's third or second letter decides fast; the order is that of the contract.
_NAMES = "|".join(map(_either_case, ("password", "passwd", "secret", "token", "api_?key")))
ASSIGN = re.compile(rf"({_NAMES})[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)")
ACCESS = re.compile("AKIA[A-Z0-9]{16,}")
HEX = re.compile("[0-9a-f]{24,}")
#: A run with its further lines, which end as they are or escaped.
RUN = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{24,}(?:(?:(?:\\r)?\\n|\r?\n)[ \t]*[A-Za-z0-9+/_-]+)*={0,2}")
_BREAK = re.compile(r"(?:(?:\\r)?\\n|\r?\n)[ \t]*")
LEAST_RUN = 40
#: How a sequence begins: its tag and length, then a version or a scheme.
_DER_BASE64 = re.compile("(?=M(?:[A-H][AEIMQUYcgkosw048][Cw]|I[E-T]))")
_DER_HEX = re.compile("(?=30(?:[0-7][0-9a-f]|81[0-9a-f]{2}|82[0-9a-f]{4}|83[0-9a-f]{6}|84[0-9a-f]{8})(?:02010|30))", re.I)
_SSH_BASE64 = re.compile("(?=b3BlbnNzaC1rZXktdjE)")
_SSH_HEX = re.compile("(?=6f70656e7373682d6b65792d763100)", re.I)
_HEX_RUN = re.compile(f"[0-9a-fA-F]{{{LEAST_RUN},}}")
PEM_BEGIN = re.compile("-----BEGIN ([A-Z0-9 ]*PRIVATE KEY)-----")
#: Schemes by which keys are encrypted: the beginnings of their object identifiers.
_SCHEMES = (bytes.fromhex("2a864886f70d0105"), bytes.fromhex("2a864886f70d010c01"))
JWT = re.compile(r"eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\.[A-Za-z0-9_-]*")
_SSH_MAGIC = b"openssh-key-v1\0"


def unbase64(text: str) -> bytes | None:
    """The bytes of a base64 or base64url run, None if it is neither."""
    text = text.rstrip("=").replace("-", "+").replace("_", "/")
    if len(text) % 4 == 1:
        return None
    try:
        return base64.b64decode(text + "=" * (-len(text) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _der_item(data: bytes, at: int, end: int) -> tuple[int, int, int] | None:
    """(tag, content start, content end) of the item at ``at``, None if it leaves [at, end)."""
    if at + 2 > end:
        return None
    tag, size, at = data[at], data[at + 1], at + 2
    if size & 0x80:
        width = size & 0x7F
        if not 1 <= width <= 4 or at + width > end:
            return None
        size, at = int.from_bytes(data[at : at + width], "big"), at + width
    return (tag, at, at + size) if at + size <= end else None


def is_private_der(data: bytes) -> bool:
    """Whether ``data`` is one sequence of well-nested items that starts with a small version number."""
    outer = _der_item(data, 0, len(data))
    if not outer or outer[0] != 0x30 or outer[2] != len(data):
        return False
    at, items = outer[1], []
    while at < outer[2]:
        item = _der_item(data, at, outer[2])
        if not item:
            return False
        if item[0] in (0x30, 0x31):  # nested items fill their parent too
            inner = item[1]
            while inner < item[2]:
                child = _der_item(data, inner, item[2])
                if not child:
                    return False
                inner = child[2]
        items.append(item)
        at = item[2]
    if len(items) < 2 or items[0][0] != 0x02 or items[0][2] - items[0][1] != 1 or data[items[0][1]] > 3:
        return False
    tags = [t for t, _, _ in items]
    whole_numbers = len(items) >= 6 and set(tags[:6]) == {0x02}  # RSA, DSA
    wrapped = tags[1] == 0x30 and 0x04 in tags[2:3]  # algorithm, then the key's octets
    curve = tags[1] == 0x04 and all(t in (0xA0, 0xA1) for t in tags[2:])
    return whole_numbers or wrapped or curve


def is_encrypted_der(data: bytes) -> bool:
    """Whether ``data`` is one sequence of an encryption scheme and the octets of a key."""
    outer = _der_item(data, 0, len(data))
    if not outer or outer[0] != 0x30 or outer[2] != len(data):
        return False
    scheme = _der_item(data, outer[1], outer[2])
    name = scheme and scheme[0] == 0x30 and _der_item(data, scheme[1], scheme[2])
    octets = scheme and _der_item(data, scheme[2], outer[2])
    return bool(name and name[0] == 0x06 and data[name[1] : name[2]].startswith(_SCHEMES) and octets and octets[0] == 0x04 and octets[2] == outer[2])


def der_size(head: bytes) -> int:
    """Bytes of the sequence that begins with ``head``, 0 if its length can't be read."""
    if len(head) < 2 or head[0] != 0x30:
        return 0
    if not head[1] & 0x80:
        return 2 + head[1]
    width = head[1] & 0x7F
    return 2 + width + int.from_bytes(head[2 : 2 + width], "big") if 1 <= width <= 4 and len(head) >= 2 + width else 0


def is_ssh_private(data: bytes) -> bool:
    """Whether ``data`` starts as an OpenSSH private key whose strings stay inside it."""
    return ssh_size(data) > 0


def ssh_size(data: bytes) -> int:
    """Bytes of the OpenSSH private key that ``data`` starts with, 0 for none."""
    if not data.startswith(_SSH_MAGIC):
        return 0
    at = len(_SSH_MAGIC)
    for part in range(5):  # cipher, key derivation, its options; a count; public key, private part
        if part == 3:
            at += 4
        if at + 4 > len(data):
            return 0
        at += 4 + int.from_bytes(data[at : at + 4], "big")
        if at > len(data):
            return 0
    return at


def is_signed_token(run: str) -> bool:
    """Whether the first two of three dot-separated parts decode to JSON objects, the first naming its algorithm."""
    parts = run.split(".")
    try:
        head, body = (json.loads(unbase64(p) or b"") for p in parts[:2])
    except (ValueError, RecursionError):
        return False
    return isinstance(head, dict) and isinstance(head.get("alg"), str) and isinstance(body, dict) and (bool(parts[2]) or head["alg"] == "none")


def base_spans(text: str) -> list[tuple[int, int, str]]:
    # The longest runs decide: a hex or access run of full length is never hidden by a shorter one.
    found = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6] if ":" in text or "=" in text else []
    if "AKIA" in text:
        found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text)]
    return found + [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]


def pem_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    for m in PEM_BEGIN.finditer(text):
        close = text.find("-----", m.end())
        mark = f"-----END {m[1]}-----"
        if close < 0 or not text.startswith(mark, close):
            # a header's dashes never come five in a row: this block has no end
            continue
        lines = re.split(r"\\r\\n|\\[nr]|[\r\n]", text[m.end() : close])
        headers = [x for x in lines if ":" in x]
        data = unbase64(re.sub(r"\s", "", "".join(x for x in lines if ":" not in x)))
        sealed = any("ENCRYPTED" in x for x in headers) and any(x.strip().startswith("DEK-Info:") for x in headers)
        if data and (is_private_der(data) or is_ssh_private(data) or is_encrypted_der(data) or (sealed and len(data) % 8 == 0)):
            found.append((m.start(), close + len(mark), "pem"))
    return found


def _structures(run: str, chars, der: re.Pattern, ssh: re.Pattern, decode) -> list[tuple[int, int, str]]:
    """Spans in ``run`` of structures; ``chars`` gives the characters that a number of bytes takes."""
    found, done = [], 0
    for m in der.finditer(run):
        at = m.start()
        if at < done:
            continue
        size = der_size(decode(run[at : at + 12]) or b"")
        end = at + chars(size)
        if size and end <= len(run) and (data := decode(run[at:end])) and (is_private_der(data[:size]) or is_encrypted_der(data[:size])):
            found.append((at, end, "der"))
            done = end
    for m in ssh.finditer(run):
        rest = run[m.start() :]
        data = decode(rest[:-1] if len(rest) % 4 == 1 else rest)
        if data and (size := ssh_size(data)):
            found.append((m.start(), m.start() + chars(size), "ssh"))
    return found


def _unhex(text: str) -> bytes:
    return bytes.fromhex(text[: len(text) & ~1])


def encoded_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    for m in RUN.finditer(text):
        if m.end() - m.start() < LEAST_RUN:
            continue
        whole = m[0].rstrip("=")
        starts, at, size, parts = [0], [0], 0, []  # where each line starts, joined and in the run
        last = 0
        for gap in _BREAK.finditer(whole):
            parts.append(whole[last : gap.start()])
            size += gap.start() - last
            last = gap.end()
            starts.append(size)
            at.append(last)
        run = "".join([*parts, whole[last:]])
        spans_ = _structures(run, lambda n: -(-n * 4 // 3), _DER_BASE64, _SSH_BASE64, unbase64)
        for h in _HEX_RUN.finditer(run):
            spans_ += [(h.start() + s, h.start() + e, k) for s, e, k in _structures(h[0], lambda n: 2 * n, _DER_HEX, _SSH_HEX, _unhex)]

        def place(i: int) -> int:
            k = bisect.bisect_right(starts, i) - 1
            return m.start() + at[k] + i - starts[k]

        for s, e, kind in spans_:
            end = place(e - 1) + 1
            while end < m.end() and text[end] == "=":
                end += 1
            found.append((place(s), end, kind))
    return found


def confirmed_spans(text: str) -> list[tuple[int, int, str]]:
    """Spans that decode and parse."""
    found = pem_spans(text) if "PRIVATE KEY-----" in text else []
    # what a block of its own kind already holds is not named twice
    found += [x for x in encoded_spans(text) if not any(s <= x[0] and x[1] <= e for s, e, _ in found)]
    if "eyJ" in text:
        found += [(m.start(), m.end(), "jwt") for m in JWT.finditer(text) if is_signed_token(m[0])]
    return found


def spans(text: str | None) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """(base spans, all spans) of a text, by start, then kind."""
    text = text or ""
    order = lambda s: (s[0], _RANK[s[2]], s[1])
    base = sorted(base_spans(text), key=order)
    return base, sorted(base + confirmed_spans(text), key=order)


def joined(found: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in found)


def scan(docs: DataFrame) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): counts of base spans, their hash, and all spans."""

    def run(batches):
        for batch in batches:
            rows = []
            for text in batch.column("text"):
                base, every = spans(text.as_py())
                kinds = [k for _, _, k in base]
                rows.append((*(kinds.count(k) for k in KINDS[:3]), hashlib.sha256(joined(base).encode()).hexdigest(), joined(every)))
            columns = list(zip(*rows)) or [()] * 5
            yield pa.RecordBatch.from_arrays([batch.column("doc_id")] + [pa.array(c, pa.int64()) for c in columns[:3]] + [pa.array(c, pa.string()) for c in columns[3:]], names)

    names = ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"]
    return docs.selectExpr("cast(doc_id as long) as doc_id", "text").mapInArrow(run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def hide(text: str, mark: str) -> str:
    out, at = [], 0
    for start, end, _ in spans(text)[1]:
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join(out) + text[at:]


def redact(docs: DataFrame, mark: str = "[SECRET]") -> DataFrame:
    """``docs`` with every span of its texts replaced by ``mark``; other texts and columns stay.

    ``n_chars``, if there, is the new length of a changed text.
    """

    def run(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            new = [hide(t, mark) if t else t for t in texts]
            columns = dict(zip(batch.schema.names, batch.columns))
            columns["text"] = pa.array(new, batch.schema.field("text").type)
            if "n_chars" in columns:
                old = columns["n_chars"].to_pylist()
                columns["n_chars"] = pa.array([o if a == b else len(b) for o, a, b in zip(old, texts, new)], batch.schema.field("n_chars").type)
            yield pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

    return docs.mapInArrow(lean(run), docs.schema)
