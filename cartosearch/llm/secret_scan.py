"""Secret scans with structural confirmation.

Pattern hits (assignments, access keys, hex runs) are reported as they stand. Candidates whose mere look
says little, base64 or hex runs and dotted tokens, are decoded first and reported only where the
decoded bytes parse: a DER key whose nested lengths fit, a length-prefixed key file, a signed token whose
header and payload are JSON objects. A key may begin anywhere in a run and go on over line ends, also escaped ones: its
outermost length says where it ends.

Null or empty text: no findings, all counts 0, empty span list. Rows are handled one by one, so ties,
repeated rows and an empty table need no rule; whole texts are scanned however long.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re

from pyspark.sql import DataFrame

from . import textblocks as tb

#: Order of kinds among spans that start together: the base kinds, then those of the confirmation.
KINDS = ("assign", "access", "hex", "jwt", "key", "hexkey", "pem")
_RANK = {k: i for i, k in enumerate(KINDS)}

ASSIGN = re.compile(r"""(?ia:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")
#: Where a key may begin, at any place of a run: a sequence of 30 bytes or more, or the magic of a key file.
BASE64_HEAD = re.compile(r"M[A-P][A-Za-z0-9+/_-]{8}|b3BlbnNzaC1rZXktdjEA")
HEX_HEAD = re.compile(r"(?=(30(?:82[0-9a-f]{4}|81[89a-f][0-9a-f]|[2-7][0-9a-f])(?:02010[01]|30)|6f70656e7373682d6b65792d763100))", re.I)
BASE64_PART = re.compile(r"[A-Za-z0-9+/_-]+")
HEX_PART = re.compile(r"[0-9a-fA-F]+")
#: A line end inside a key, as it stands or escaped.
LINE_END = re.compile(r"\r?\n[ \t]*|(?:\\r)?\\n")
DOTTED = re.compile(r"[A-Za-z0-9_-]{16,}\.[A-Za-z0-9_-]{2,}\.[A-Za-z0-9_-]*")
#: A base64 character pair that begins with an opening brace.
BRACE = re.compile(r"(?=e[w-z0-9_-])")
PEM = re.compile(r"-----BEGIN ([A-Z ]*)PRIVATE KEY-----((?:[A-Za-z0-9+/=\s]|\\r|\\n)+)-----END \1PRIVATE KEY-----")
#: Object identifiers of password-based encryption (the key is wrapped), as prefixes.
WRAPPED = (bytes.fromhex("2a864886f70d0105"), bytes.fromhex("2a864886f70d010c01"))
MAGIC = b"openssh-key-v1\0"


def _unbase64(text: str) -> bytes | None:
    body = text.rstrip("=").replace("-", "+").replace("_", "/")
    if len(body) % 4 == 1:
        return None
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def _elements(data: bytes, at: int, end: int) -> list[tuple[int, int, int]] | None:
    """(tag, start, end) of the DER elements that fill data[at:end] exactly, else None."""
    out = []
    while at < end:
        if at + 2 > end:
            return None
        tag, size, at = data[at], data[at + 1], at + 2
        if size & 0x80:
            k = size & 0x7F
            if not 1 <= k <= 4 or at + k > end or data[at] == 0:
                return None
            size, at = int.from_bytes(data[at : at + k], "big"), at + k
            if size < 0x80:
                return None
        if at + size > end:
            return None
        out.append((tag, at, at + size))
        at += size
    return out


def _der_key(data: bytes) -> bool:
    """RSA (nine integers), DSA (six), EC (integer 1 and an octet string), a wrapped key around any, or an encrypted one."""
    top = _elements(data, 0, len(data))
    if not top or len(top) != 1 or top[0][0] != 0x30:
        return False
    inner = _elements(data, *top[0][1:])
    if not inner:
        return False
    tags = [x[0] for x in inner]
    if tags == [0x30, 0x04]:
        kind = _elements(data, *inner[0][1:])
        return bool(kind) and kind[0][0] == 0x06 and data[kind[0][1] : kind[0][2]].startswith(WRAPPED) and inner[1][2] - inner[1][1] >= 16
    if inner[0][0] != 0x02 or data[inner[0][1] : inner[0][2]] not in (b"\0", b"\1"):
        return False
    if tags[:9] == [0x02] * 9 or tags == [0x02] * 6:
        return all(x[2] > x[1] for x in inner) and sum(x[2] - x[1] for x in inner) >= 32
    if tags[:2] == [0x02, 0x04] and set(tags[2:]) <= {0xA0, 0xA1}:
        return 20 <= inner[1][2] - inner[1][1] <= 66
    if tags[:3] == [0x02, 0x30, 0x04]:
        kind, body = _elements(data, *inner[1][1:]), _elements(data, *inner[2][1:])
        return bool(kind) and kind[0][0] == 0x06 and bool(body) and len(body) == 1 and body[0][0] in (0x30, 0x02, 0x04)
    return False


def _file_size(data: bytes) -> int | None:
    """Bytes of a key file of 32-bit length-prefixed fields after its magic, if data holds that many, one key being in it."""
    at = len(MAGIC)
    for field in ("cipher", "kdf", "options", "count", "public", "private"):
        if at + 4 > len(data):
            return None
        size, at = int.from_bytes(data[at : at + 4], "big"), at + 4
        if field == "count":
            if size != 1:
                return None
        else:
            at += size
    return at if at <= len(data) else None


def _length_prefixed_key(data: bytes) -> bool:
    return data.startswith(MAGIC) and _file_size(data) == len(data)


def _sequence_size(head: bytes) -> int | None:
    """Bytes of the DER sequence that begins like this, header included; None for what no key begins with."""
    if len(head) < 6 or head[0] != 0x30 or head[1] > 0x82 or head[1] == 0x80:
        return None
    skip, size = (2, head[1]) if head[1] < 0x80 else (3, head[2]) if head[1] == 0x81 else (4, head[2] << 8 | head[3])
    return skip + size if skip + size >= 30 and head[skip] in (0x02, 0x30) else None


def is_key(data: bytes | None) -> bool:
    return bool(data) and (_der_key(data) if data[0] == 0x30 else _length_prefixed_key(data))


def _json(part: str) -> object:
    try:
        return json.loads(_unbase64(part) or b"")
    except (ValueError, RecursionError):
        return None


def signed_token(text: str) -> int | None:
    """Where in the first of three dotted parts a signed token's header begins: JSON that names an algorithm, before a
    payload of JSON and a signature. None: it is no token, however it looks."""
    head, body, signature = text.split(".")
    if not isinstance(_json(body), dict):
        return None
    for m in BRACE.finditer(head):
        if (_unbase64(head[m.start() : m.start() + 4]) or b"")[1:2] not in (b'"', b" ", b"\n", b"\r", b"\t"):
            continue
        header = _json(head[m.start() :])
        if isinstance(header, dict) and isinstance(header.get("alg"), str):
            return m.start() if header["alg"].lower() == "none" or _unbase64(signature) else None
    return None


def _tokens(text: str) -> list[tuple[int, int, str]]:
    found, at = [], 0
    while m := DOTTED.search(text, at):
        begin = signed_token(m[0])
        if begin is not None:
            found.append((m.start() + begin, m.end(), "jwt"))
        # What is no token may hold one from its second part on.
        at = m.end() if begin is not None else m.start() + m[0].index(".") + 1
    return found


def _gather(text: str, at: int, count: int | None, part: re.Pattern) -> tuple[str, int]:
    """`count` characters (None: all) of the runs from `at` on, across line ends, and where they end."""
    out, have = [], 0
    while count is None or have < count:
        m = part.match(text, at)
        if not m:
            break
        take = m[0] if count is None else m[0][: count - have]
        out.append(take)
        have += len(take)
        at += len(take)
        if len(take) == len(m[0]) and (count is None or have < count):
            gap = LINE_END.match(text, at)
            if not gap or not part.match(text, gap.end()):
                break
            at = gap.end()
    return "".join(out), at


def _encoded_keys(text: str) -> list[tuple[int, int, str]]:
    """Keys in base64 or hex that begin anywhere in a run and may go on over line ends: their own lengths say where they end."""
    found, done = [], 0
    for m in BASE64_HEAD.finditer(text):
        at = m.start()
        if at < done:
            continue
        if m[0][0] == "b":
            run, _ = _gather(text, at, None, BASE64_PART)
            data = _unbase64(run[: len(run) // 4 * 4] if len(run) % 4 == 1 else run)
            size = data and _file_size(data)
        else:
            size = _sequence_size(_unbase64(m[0][:8]) or b"")
        if not size:
            continue
        run, end = _gather(text, at, -(-size * 8 // 6), BASE64_PART)
        data = _unbase64(run) if len(run) * 6 // 8 >= size else None
        if data and is_key(data[:size]):
            while end < len(text) and text[end] == "=":
                end += 1
            found.append((at, end, "key"))
            done = end
    done = 0
    for m in HEX_HEAD.finditer(text):
        at = m.start()
        if at < done:
            continue
        if m[1][0] in "36" and m[1][1] == "0":
            head = bytes.fromhex(text[at : at + 12]) if len(m[1]) >= 12 else bytes.fromhex(m[1][: len(m[1]) // 2 * 2].ljust(12, "0"))
            size = _sequence_size(head)
        else:
            run, _ = _gather(text, at, None, HEX_PART)
            size = _file_size(bytes.fromhex(run[: len(run) // 2 * 2]))
        if not size:
            continue
        run, end = _gather(text, at, 2 * size, HEX_PART)
        if len(run) == 2 * size and is_key(bytes.fromhex(run)):
            found.append((at, end, "hexkey"))
            done = end
    return found


def base_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    if "=" in text or ":" in text:
        found += [(*m.span(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        found += [(*m.span(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    return found + [(*m.span(), "hex") for m in HEX.finditer(text)]


def confirmed_spans(text: str) -> list[tuple[int, int, str]]:
    found = (_tokens(text) if "." in text else []) + _encoded_keys(text)
    if "-----BEGIN" in text:
        found += [(*m.span(), "pem") for m in PEM.finditer(text) if is_key(_unbase64(re.sub(r"\\[rn]|\s", "", m[2])))]
    return found


def _ordered(spans: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    return sorted(spans, key=lambda s: (s[0], _RANK[s[2]], s[1]))


def _joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{kind}:{start}:{end}" for start, end, kind in _ordered(spans))


SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string, n_confirmed long"


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: counts of base findings, their digest, and all spans in code points."""

    def make(part):
        rows = []
        for text in tb.texts(part):
            base, more = base_spans(text), confirmed_spans(text)
            kinds = [k for _, _, k in base]
            rows.append((kinds.count("assign"), kinds.count("access"), kinds.count("hex"), hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(base + more), len(more)))
        names = [x.split()[0] for x in SCHEMA.split(", ")][1:]
        return {"doc_id": tb.column(part, "doc_id")} | dict(zip(names, map(list, zip(*rows))))

    return tb.per_slice(docs, make, SCHEMA)


def redacted(text: str) -> str:
    """The text with every finding replaced by its kind; overlapping findings become one, named by the first."""
    out, at = [], 0
    for start, end, kind in _ordered(base_spans(text) + confirmed_spans(text)):
        if start >= at:
            out += [text[at:start], f"[{kind}]"]
        at = max(at, end)
    return "".join([*out, text[at:]])


def redact(docs: DataFrame) -> DataFrame:
    """All rows and columns of docs; findings in text are masked and n_chars, if there, follows. Null stays null."""
    import pyarrow as pa
    import pyarrow.compute as pc

    names, schema = docs.columns, docs.schema

    def run(batches):
        for batch in batches:
            for part in tb.text_slices(batch):
                given = tb.column(part, "text")
                new = pa.array([None if t is None else redacted(t) for t in given.to_pylist()], given.type)
                part = part.set_column(names.index("text"), part.schema.field(names.index("text")), new)
                if "n_chars" in names:
                    k = names.index("n_chars")
                    part = part.set_column(k, part.schema.field(k), pc.utf8_length(new).cast(part.schema.field(k).type))
                yield part

    return docs.mapInArrow(run, schema)
