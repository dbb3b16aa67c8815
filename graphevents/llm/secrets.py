"""Secret scans with structural confirmation.

Plain patterns give the base spans. Runs of base64, base64url or hex characters are then decoded and reported only when what
they decode to has the structure of a secret: a private key in nested length-prefixed (DER) form, a key in the wire format of
the SSH tools, or a signed token whose header is JSON with an algorithm. Armoured keys are decoded the same way; the header lines
of older armour are read, and a body that they declare encrypted must fill whole cipher blocks. The outer length of a key tells
where it ends, so a key may be wrapped over lines, begin anywhere in a run of hex digits, and be followed by other text.
"""

from __future__ import annotations

import base64
import binascii
import bisect
import hashlib
import json
import re
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import document, slices, table, texts_of, with_text

# The base patterns and the least length of each.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
KINDS = ("assign", "access", "hex", "private_key", "ssh_key", "signed_token")

LONG_HEX = re.compile(r"[0-9a-f]{32,}")
ARMOUR = re.compile(r"-----BEGIN ([A-Z0-9 ]*PRIVATE KEY)-----\s*((?:[A-Za-z][A-Za-z0-9-]*:[^\n]*(?:\n[ \t][^\n]*)*\n\s*)*)([A-Za-z0-9+/=\s]*?)-----END \1-----")
TOKEN = re.compile(r"(?<![A-Za-z0-9_.-])([A-Za-z0-9_-]{8,})\.([A-Za-z0-9_-]{2,})\.([A-Za-z0-9_-]*)(?![A-Za-z0-9_-])")
#: A run of base64 characters, on through following lines that begin with such characters.
BASE64 = re.compile(r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{40,}(?:[ \t]*\r?\n[ \t]*[A-Za-z0-9+/_-]+)*={0,2}")
#: Where in such a run a key may begin: a line whose first byte is 0x30, or with the magic of the SSH tools.
LINE = re.compile(r"(?:^|(?<=[\s]))(?=M[A-P]|b3BlbnNza)")
ANY_HEX = re.compile(r"[0-9A-Fa-f]{64,}")
#: In a run of hex digits: a sequence with a length of one byte or of one to four more, or the same magic.
HEX_START = re.compile(r"(?=30(?:[2-7][0-9A-F]|8[1-4])|6F70656E7373682D6B6579)", re.I)
#: A text that none of these occurs in can hold no span: RE2, on the whole Arrow column at once.
MAY = {
    "assign": r"(?i)passw(?:or)?d|secret|token|api_?key",
    "access": r"AKIA",
    "hex": r"[0-9a-f]{32}",
    "deep": r"[A-Za-z0-9+/_-]{40}|-----BEGIN |[A-Za-z0-9_-]{8}\.[A-Za-z0-9_-]{2,}\.",
}
#: A key in the form of the SSH tools, whose parts tell its length only one after the other, has at most so many bytes.
SSH_BYTES = 1 << 16
#: Object identifiers of public-key algorithms, DER-encoded: RSA, EC, Ed25519, X25519.
KEY_KINDS = (bytes.fromhex("2a864886f70d010101"), bytes.fromhex("2a8648ce3d0201"), bytes.fromhex("2b6570"), bytes.fromhex("2b656e"))


def unbase64(text: str) -> bytes | None:
    plain = re.sub(r"\s+", "", text).replace("-", "+").replace("_", "/").rstrip("=")
    if len(plain) % 4 == 1:
        return None
    try:
        return base64.b64decode(plain + "=" * (-len(plain) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def der_items(data: bytes) -> list[tuple[int, bytes]] | None:
    """The (tag, content) items that fill ``data`` exactly, or None where the lengths do not nest."""
    items, at = [], 0
    while at < len(data):
        if at + 2 > len(data):
            return None
        tag, size, at = data[at], data[at + 1], at + 2
        if size & 0x80:
            n = size & 0x7F
            if not 1 <= n <= 4 or at + n > len(data):
                return None
            size, at = int.from_bytes(data[at : at + n], "big"), at + n
            if size < 0x80:
                return None  # not the shortest form
        if at + size > len(data):
            return None
        items.append((tag, data[at : at + size]))
        at += size
    return items


def is_private_key(data: bytes) -> bool:
    """An RSA, EC or algorithm-wrapped private key (encrypted or not): one sequence whose parts are of the right kinds."""
    outer = der_items(data)
    if not outer or len(outer) != 1 or outer[0][0] != 0x30 or not (parts := der_items(outer[0][1])):
        return False
    tags = [t for t, _ in parts]
    if tags[0] == 0x02 and len(parts) >= 9 and set(tags[:9]) == {0x02}:  # version, modulus, exponents, primes
        return len(parts[1][1]) >= 32
    if tags[:3] == [0x02, 0x30, 0x04]:  # version, algorithm, key
        kind = der_items(parts[1][1])
        return bool(kind) and kind[0][0] == 0x06 and kind[0][1] in KEY_KINDS
    if tags[:2] == [0x02, 0x04] and parts[0][1] == b"\x01":  # version 1, octets of an EC key
        return 16 <= len(parts[1][1]) <= 80
    if tags == [0x30, 0x04]:  # encryption scheme, encrypted key
        kind = der_items(parts[0][1])
        return bool(kind) and kind[0][0] == 0x06 and len(parts[1][1]) >= 32
    return False


def der_length(data: bytes) -> int | None:
    """Bytes of the sequence that ``data`` begins with, by its outer length."""
    if len(data) < 2 or data[0] != 0x30:
        return None
    if data[1] < 0x80:
        return 2 + data[1]
    n = data[1] & 0x7F
    return 2 + n + int.from_bytes(data[2 : 2 + n], "big") if 1 <= n <= 4 and len(data) >= 2 + n else None


def ssh_length(data: bytes) -> int | None:
    """Bytes of the private form of the SSH tools that ``data`` begins with: its magic, length-prefixed cipher, derivation and options, a
    key count, as many public keys and the private part."""
    magic = b"openssh-key-v1\x00"
    if not data.startswith(magic):
        return None
    at, left = len(magic), 3
    while left:
        at += 4 + int.from_bytes(data[at : at + 4], "big")
        if at + 4 > len(data):
            return None
        left -= 1
    keys, at = int.from_bytes(data[at : at + 4], "big"), at + 4
    if not 1 <= keys <= 16:
        return None
    for _ in range(keys + 1):
        if at + 4 > len(data):
            return None
        at += 4 + int.from_bytes(data[at : at + 4], "big")
    return at if at <= len(data) else None


def key_in(data: bytes | None) -> tuple[str, int] | None:
    """(kind, bytes) of the key that ``data`` begins with."""
    if not data:
        return None
    n = der_length(data)
    if n is not None and n <= len(data) and is_private_key(data[:n]):
        return "private_key", n
    n = ssh_length(data)
    return ("ssh_key", n) if n is not None else None


def is_signed_token(head: str, body: str) -> bool:
    try:
        header = json.loads(unbase64(head) or b"")
        return isinstance(header, dict) and isinstance(header.get("alg"), str) and isinstance(json.loads(unbase64(body) or b""), dict)
    except ValueError:
        return False


def is_encrypted_armour(head: str, body: bytes | None) -> bool:
    """Header lines that name a cipher and its start value, over whole blocks of that cipher."""
    lines = dict(x.split(":", 1) for x in head.splitlines() if ":" in x)
    cipher, _, start = lines.get("DEK-Info", "").strip().partition(",")
    if lines.get("Proc-Type", "").strip() != "4,ENCRYPTED" or not re.fullmatch(r"(?:[0-9A-Fa-f]{2}){8,16}", start.strip()):
        return False
    return bool(body) and len(body) >= 32 and len(body) % (16 if "AES" in cipher.upper() else 8) == 0


def deep_spans(text: str) -> list[tuple[int, int, str]]:
    found = []
    for m in ARMOUR.finditer(text):
        body = unbase64(m[3])
        if (key := key_in(body)) or is_encrypted_armour(m[2], body):
            found.append((m.start(), m.end(), key[0] if key else "private_key"))
    inside = lambda a, b: any(x <= a and b <= y for x, y, _ in found)
    for m in TOKEN.finditer(text):
        if is_signed_token(m[1], m[2]):
            found.append((m.start(), m.end(), "signed_token"))
    for m in BASE64.finditer(text):
        run = m[0]
        at = [i for i, c in enumerate(run) if not c.isspace() and c != "="]
        plain, done, k = "".join([run[i] for i in at]), 0, 0
        for line in LINE.finditer(run):
            a = line.start()
            if a < done or inside(m.start() + a, m.end()):
                continue
            k = bisect.bisect_left(at, a, k)
            n = der_length(unbase64(plain[k : k + 12]) or b"")
            n = SSH_BYTES if n is None else n
            if (key := key_in(decoded_from(plain[k : k + (n * 4 + 2) // 3]))) is None:
                continue
            done = at[k + (key[1] * 4 + 2) // 3 - 1] + 1
            while done < len(run) and run[done] == "=":
                done += 1
            found.append((m.start() + a, m.start() + done, key[0]))
    for m in ANY_HEX.finditer(text):
        run = m[0]
        done = 0
        for start in HEX_START.finditer(run):
            a = start.start()
            if a < done or inside(m.start() + a, m.end()):
                continue
            n = der_length(bytes.fromhex(run[a : a + 12]))
            if n is not None and 2 * n > len(run) - a:
                continue  # longer than the run
            upto = a + 2 * (n if n is not None else min(SSH_BYTES, (len(run) - a) // 2))
            if key := key_in(bytes.fromhex(run[a:upto])):
                done = a + 2 * key[1]
                found.append((m.start() + a, m.start() + done, key[0]))
    return found


def decoded_from(text: str) -> bytes | None:
    """The bytes of a run of base64 characters; one that is left over at its end tells nothing."""
    return unbase64(text[:-1] if len(text) % 4 == 1 else text)


def spans_of(text: str, may: tuple[bool, bool, bool, bool] = (True, True, True, True)) -> list[tuple[int, int, str]]:
    """(start, end, kind) by start, then kind; code points, end exclusive."""
    found = []
    if may[0]:
        found += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if may[1]:
        found += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if len(m[0]) >= 16]
    if may[2]:
        # Runs of these characters are maximal either way, so the short ones need not be looked at.
        found += [(m.start(), m.end(), "hex") for m in LONG_HEX.finditer(text)]
    if may[3]:
        found += deep_spans(text)
    return sorted(set(found), key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def scanned(docs: DataFrame, keep: list, whole: bool = False) -> DataFrame:
    """``keep`` beside ``found``, an array of (start, end, kind) of every whole text, and ``hidden``, the text with its spans replaced
    (null where there are none). Null and empty texts have none. One Python worker a task does both."""
    rows, place = with_text(docs, keep, whole)
    kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches, place):
            texts = pc.fill_null(texts_of(b, place), "")
            may = {k: pc.match_substring_regex(texts, p) for k, p in MAY.items()}
            some = pc.or_(pc.or_(may["assign"], may["access"]), pc.or_(may["hex"], may["deep"])).to_numpy(zero_copy_only=False)
            may = [may[k].to_numpy(zero_copy_only=False) for k in MAY]
            found: list = [[] for _ in range(b.num_rows)]
            hidden: list = [None] * b.num_rows
            for i in some.nonzero()[0]:
                text = texts[int(i)].as_py()
                got = spans_of(text, tuple(m[i] for m in may))
                found[i] = [{"start": a, "end": e, "kind": k} for a, e, k in got]
                if got and whole:
                    hidden[i] = redacted(text, [(a, e) for a, e, _ in got])
            yield pa.RecordBatch.from_arrays([b.column("row"), pa.array(found, kind), pa.array(hidden, pa.string())], ["row", "found", "hidden"])

    schema = f"row {rows.schema['row'].dataType.simpleString()}, found array<struct<start: long, end: long, kind: string>>, hidden string"
    return rows.mapInArrow(run, schema).select("row.*", "found", "hidden")


def report(docs: DataFrame) -> DataFrame:
    """One row a document: doc_id, n_assign, n_access, n_hex, base_sha256, spans. Rows are judged each on its own, so ties and repeats
    do not matter; null and empty texts have no spans and the digest of nothing; an empty table gives an empty result."""
    rows = scanned(docs, [F.col("doc_id").alias("doc_id")])
    line = lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))
    text = lambda xs: F.concat_ws(",", F.transform(xs, line))
    base = F.filter("found", lambda x: x["kind"].isin("assign", "access", "hex"))
    count = lambda k: F.size(F.filter("found", lambda x: x["kind"] == k)).cast("long")
    return rows.select(
        "doc_id", *[count(k).alias(f"n_{k}") for k in ("assign", "access", "hex")],
        F.sha2(text(base).cast("binary"), 256).alias("base_sha256"), text(F.col("found")).alias("spans"),
    )


def redacted(text: str, spans: list[tuple[int, int]], mark: str = "[secret]") -> str:
    """``text`` with each merged span replaced."""
    out, at = [], 0
    for a, b in sorted(spans):
        if b <= at:
            continue
        if a >= at:
            out += [text[at:a], mark]
        at = b
    return "".join([*out, text[at:]])


def clean_documents(docs: DataFrame) -> DataFrame:
    """All rows of ``docs``; spans in ``text`` are replaced, and ``n_chars``, where there is one, counts the new text."""
    packed = scanned(docs, [document(docs)], whole=True)
    hit = F.col("hidden").isNotNull()
    changed = {"text": F.col("hidden"), "n_chars": F.length("hidden")}
    own = lambda c: F.col(f"document.`{c}`")
    return packed.select(*[F.when(hit, changed[c].cast(docs.schema[c].dataType)).otherwise(own(c)).alias(c) if c in changed else own(c).alias(c) for c in docs.columns])


def op9(spark, sf_dir: str) -> DataFrame:
    """Secrets of all ``documents``; odd rows as in ``report``."""
    return report(table(spark, sf_dir, "documents"))


def digest(spans) -> str:
    return hashlib.sha256(joined([s for s in spans if s[2] in KINDS[:3]]).encode()).hexdigest()
