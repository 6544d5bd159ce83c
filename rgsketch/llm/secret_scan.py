"""Secret scan with structural confirmation.

Three base patterns (assign, access, hex) give leftmost non-overlapping matches. On top, candidates in base64, base64url or
hex are decoded and reported only when their structure holds: private keys as DER with consistent nested lengths (PKCS 1,
PKCS 8, also encrypted by a password, SEC 1, DSA), OpenSSH key files with consistent length fields, and signed tokens whose header is JSON naming an
algorithm and whose payload is JSON. A vectorised pass over the bytes finds the rows that can match at all; the patterns
themselves run on those rows' whole texts.

Edge cases: a null text counts as empty and gives no span; texts of any length are scanned whole; offsets are code points,
end exclusive; repeated rows give repeated results; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from rgsketch.llm.common import chunks, utf8

# The three base patterns and the least lengths of their matches.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LEAST = {"assign": 6, "access": 20, "hex": 24}
KINDS = ("assign", "access", "hex", "token", "der_key", "ssh_key", "hex_key")

TOKEN = re.compile(r"(?<![A-Za-z0-9_-])eyJ[A-Za-z0-9_-]{6,}\.[A-Za-z0-9_-]{2,}\.[A-Za-z0-9_-]*")
#: Between two lines of a key: line ends, plain, after a backslash or as written in JSON and .env files, with indents.
BREAK = r"[ \t]*(?:\\?[\r\n]{1,2}|(?:\\+[nr]){1,2})[ \t]*"
LINE_BREAK = re.compile(BREAK)
#: Lines in base64, then in base64url; the n of a written line end begins no line.
BLOBS = [re.compile(rf"(?:(?<![{c}])(?!(?<=\\)[nr])|(?<=\\[nr]))[{c}]{{40,}}(?:{BREAK}[{c}]+)*={{0,2}}") for c in ("A-Za-z0-9+/", "A-Za-z0-9_-")]
_STANDARD = str.maketrans("-_", "+/")
HEXBLOB = re.compile(r"(?<![0-9A-Fa-f])[0-9A-Fa-f]{48,}(?![0-9A-Fa-f])")
SSH_MAGIC = b"openssh-key-v1\0"
SSH_HEAD = base64.b64encode(SSH_MAGIC).decode()
#: The object identifiers under which encryption by a password stands (PKCS 5 and PKCS 12).
PASSWORD_SCHEMES = (bytes.fromhex("2a864886f70d0105"), bytes.fromhex("2a864886f70d010c01"))
KEYWORDS = ("password", "passwd", "secret", "token", "api")


def der(data: bytes, at: int = 0, end: int | None = None) -> list[tuple[int, int, int]] | None:
    """Elements (tag, start, end of content) that fill data[at:end] exactly; None if a length doesn't fit."""
    end, out = len(data) if end is None else end, []
    while at < end:
        if end - at < 2:
            return None
        tag, n, at = data[at], data[at + 1], at + 2
        if n == 0x80 or n > 0x84:
            return None
        if n > 0x80:
            k = n & 0x7F
            if at + k > end:
                return None
            n, at = int.from_bytes(data[at : at + k], "big"), at + k
        if at + n > end:
            return None
        out.append((tag, at, at + n))
        at += n
    return out


def is_der_key(data: bytes) -> bool:
    """A private key of PKCS 1, PKCS 8 (plain or encrypted by a password), SEC 1 or DSA by its nesting."""
    top = der(data)
    if not top or len(top) != 1 or top[0][0] != 0x30:
        return False
    inner = der(data, *top[0][1:])
    if inner and [t for t, _, _ in inner] == [0x30, 4]:
        scheme = der(data, *inner[0][1:])
        return bool(scheme) and scheme[0][0] == 6 and data[scheme[0][1] : scheme[0][2]].startswith(PASSWORD_SCHEMES)
    if not inner or len(inner) < 2 or inner[0][0] != 2 or inner[0][2] - inner[0][1] != 1 or data[inner[0][1]] > 1:
        return False
    tags = [t for t, _, _ in inner]
    if (len(tags) >= 9 or len(tags) == 6) and all(t == 2 for t in tags[:9]):
        return True
    if len(tags) >= 3 and tags[1] == 0x30 and tags[2] == 4:
        algorithm = der(data, *inner[1][1:])
        return bool(algorithm) and algorithm[0][0] == 6
    return tags[1] == 4 and data[inner[0][1]] == 1 and inner[1][2] - inner[1][1] >= 16


def is_ssh_key(data: bytes) -> bool:
    """An OpenSSH private key file: its magic, then strings whose lengths fill it."""
    if not data.startswith(SSH_MAGIC):
        return False
    at, parts = len(SSH_MAGIC), []
    while at + 4 <= len(data) and len(parts) < 3 + 1 + 2:
        if len(parts) == 3:
            parts.append(data[at : at + 4])  # number of keys
            at += 4
            continue
        n = int.from_bytes(data[at : at + 4], "big")
        if at + 4 + n > len(data):
            return False
        parts.append(data[at + 4 : at + 4 + n])
        at += 4 + n
    return len(parts) == 6 and at == len(data) and parts[3] == b"\0\0\0\1"


def _json(part: str):
    try:
        return json.loads(base64.urlsafe_b64decode(part + "=" * (-len(part) % 4)))
    except (ValueError, binascii.Error, RecursionError):
        return None


def is_token(text: str) -> bool:
    head, body, sign = text.split(".")
    header = _json(head)
    if not isinstance(header, dict) or not isinstance(header.get("alg"), str):
        return False
    return isinstance(_json(body), dict) and (bool(sign) == (header["alg"].lower() != "none"))


def base_spans(text: str) -> list[tuple[int, int, str]]:
    out = [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if len(m[0]) >= LEAST["access"]]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text) if m.end() - m.start() >= LEAST["hex"]]
    return out


def der_end(head: bytes) -> int | None:
    """Bytes of the DER sequence that begins with these six bytes, by its outer length."""
    if len(head) < 6 or head[0] != 0x30 or head[1] == 0x80 or head[1] > 0x84:
        return None
    k = max(0, head[1] - 0x80)
    return 2 + k + (int.from_bytes(head[2 : 2 + k], "big") if k else head[1])


def ssh_end(data: bytes) -> int | None:
    """Bytes of the OpenSSH private key file that data begins with, by its length fields."""
    at = len(SSH_MAGIC)
    for k in range(6):
        if k == 3:
            at += 4  # number of keys
        elif at + 4 <= len(data):
            at += 4 + int.from_bytes(data[at : at + 4], "big")
        else:
            return None
    return at


def key_spans(text: str, start: int, end: int) -> list[tuple[int, int, str]]:
    """Keys that begin with one of the lines of text[start:end] and, by their own lengths, end with one."""
    lines, at = [], start  # first and last place of each line
    stop = end - (len(text[start:end]) - len(text[start:end].rstrip("=")))
    for b in LINE_BREAK.finditer(text, start, stop):
        lines.append((at, b.start()))
        at = b.end()
    lines.append((at, stop))
    raw = "".join(text[a:b] for a, b in lines).translate(_STANDARD)
    begin, total = [], 0
    for a, b in lines:
        begin.append(total)
        total += b - a
    line_of = {b: k for k, b in enumerate([*begin[1:], total])}  # by the characters up to the line's end
    out, done = [], 0
    for k, at in enumerate(begin):
        if at < done or total - at < 40:
            continue
        if raw.startswith(SSH_HEAD, at):
            size, holds, kind = ssh_end(_decode(raw[at:])), is_ssh_key, "ssh_key"
        elif raw[at] == "M":  # the tag 0x30
            size, holds, kind = der_end(_decode(raw[at : at + 8])), is_der_key, "der_key"
        else:
            continue
        last = None if size is None else line_of.get(at + -(-size * 4 // 3))
        if last is not None and holds(_decode(raw[at : at + -(-size * 4 // 3)])[:size]):
            done = at + -(-size * 4 // 3)
            out.append((lines[k][0], end if last == len(lines) - 1 else lines[last][1], kind))
    return out


def _decode(raw: str) -> bytes:
    """The bytes of base64 of any length; what a last part of a byte lacks counts as 0."""
    return base64.b64decode(raw + "A" * (-len(raw) % 4))


def confirmed_spans(text: str) -> list[tuple[int, int, str]]:
    out = [(m.start(), m.end(), "token") for m in TOKEN.finditer(text) if is_token(m[0])]
    out += sorted({span for blob in BLOBS for m in blob.finditer(text) for span in key_spans(text, m.start(), m.end())})
    for m in HEXBLOB.finditer(text):
        if len(m[0]) % 2 == 0 and is_der_key(bytes.fromhex(m[0])):
            out.append((m.start(), m.end(), "hex_key"))
    return out


def scan(text: str | None) -> list[tuple[int, int, str]]:
    """All spans (start, end, kind) of a text, by start, then kind as listed in KINDS."""
    text = text or ""
    spans = base_spans(text) + confirmed_spans(text)
    return sorted(spans, key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


_HEXBYTE = np.zeros(256, bool)
_HEXBYTE[np.frombuffer(b"0123456789abcdef", np.uint8)] = True
_CODE = np.zeros(256, bool)
_CODE[np.frombuffer(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-.", np.uint8)] = True


def _run_rows(raw: np.ndarray, offsets: np.ndarray, table: np.ndarray, least: int) -> np.ndarray:
    """Rows that may hold a run of ``least`` bytes of the table (a run over a row's end only adds a row)."""
    stop = np.flatnonzero(~table[raw])
    edge = np.concatenate(([-1], stop, [len(raw)]))
    at = np.flatnonzero(np.diff(edge) > least)
    first = np.searchsorted(offsets, edge[at] + 1, side="right") - 1
    last = np.searchsorted(offsets, edge[at + 1] - 1, side="right") - 1
    return np.unique(np.concatenate([np.arange(a, b + 1) for a, b in zip(first, last, strict=True)])) if len(at) else at


def _rows(texts: pa.Array) -> np.ndarray:
    raw, offsets = utf8(texts)
    hit = np.zeros(len(texts), bool)
    for lo, hi in chunks(offsets):
        part, off = raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        for table, least in ((_HEXBYTE, LEAST["hex"]), (_CODE, 16)):
            hit[lo + np.minimum(_run_rows(part, off, table, least), hi - lo - 1)] = True
    return hit


def _scan_batches(batches):
    for batch in batches:
        texts = batch.column(1)
        coded = _rows(texts)
        spans = []
        for i, value in enumerate(texts):
            text = value.as_py() or ""
            low = text.lower()
            spans.append(scan(text) if coded[i] or "AKIA" in text or any(k in low for k in KEYWORDS) else [])
        kinds, starts, ends = ([[s[k] for s in row] for row in spans] for k in (2, 0, 1))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(kinds, pa.list_(pa.string())), pa.array(starts, pa.list_(pa.int64())), pa.array(ends, pa.list_(pa.int64()))], ["doc_id", "kinds", "starts", "ends"])


def find_secrets(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and the parallel arrays kinds, starts, ends; a row for every input row."""
    return df.select(df[id_col].cast("long").alias("doc_id"), df[text_col].cast("string").alias("text")).mapInArrow(_scan_batches, "doc_id long, kinds array<string>, starts array<long>, ends array<long>")


def _digest(batches):
    for batch in batches:
        ids, kinds, starts, ends = (c.to_pylist() for c in batch.columns)
        rows = [[f"{k}:{s}:{e}" for k, s, e in zip(*r, strict=True)] for r in zip(kinds, starts, ends, strict=True)]
        base = [",".join(x for x, k in zip(r, ks, strict=True) if k in LEAST) for r, ks in zip(rows, kinds, strict=True)]
        counts = [pa.array([ks.count(k) for ks in kinds], pa.int64()) for k in ("assign", "access", "hex")]
        yield pa.RecordBatch.from_arrays([batch.column(0), *counts, pa.array([hashlib.sha256(b.encode()).hexdigest() for b in base], pa.string()), pa.array([",".join(r) for r in rows], pa.string())], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])


def query(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return find_secrets(docs).mapInArrow(_digest, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
