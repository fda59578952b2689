"""Secret scan: keyword automaton first, anchored patterns at its hits, checksums last.

One Aho-Corasick pass finds the literal heads of all key formats.  Only at a
hit is a pattern tried, anchored at that place; kinds with an embedded checksum
are then validated, so that random look-alikes do not count.  Hexadecimal runs
have no literal head and are found by their own run pattern.

Spans are (kind, start, end) in code points, end exclusive.  Null and empty
texts have none; overlapping spans of different kinds are all reported.  Very
long texts and runs take time in proportion to their length; repeated rows are
each scanned; rows with a null id are returned; other columns are ignored.
"""

from __future__ import annotations

import base64
import binascii
import hashlib
import json
import re
import zlib

import ahocorasick
from pyspark.sql import DataFrame, SparkSession

from .common import LOWER, UPPER, map_texts, table

# The base kinds and the further key formats with their literal heads.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")
JWT_RUN = re.compile(r"[A-Za-z0-9_-]+")
ASSIGN_HEADS = ("password", "passwd", "secret", "token", "apikey", "api_key")
KINDS = ("assign", "access", "hex", "crc_token", "pem_key", "jwt", "chat_token", "pay_key", "cloud_key", "repo_token")
EXTRA = {
    "ghp_": ("crc_token", re.compile(r"ghp_[A-Za-z0-9]{36}(?![A-Za-z0-9])")),
    "gho_": ("crc_token", re.compile(r"gho_[A-Za-z0-9]{36}(?![A-Za-z0-9])")),
    "ghu_": ("crc_token", re.compile(r"ghu_[A-Za-z0-9]{36}(?![A-Za-z0-9])")),
    "ghs_": ("crc_token", re.compile(r"ghs_[A-Za-z0-9]{36}(?![A-Za-z0-9])")),
    "ghr_": ("crc_token", re.compile(r"ghr_[A-Za-z0-9]{36}(?![A-Za-z0-9])")),
    "npm_": ("crc_token", re.compile(r"npm_[A-Za-z0-9]{36}(?![A-Za-z0-9])")),
    "-----begin ": ("pem_key", re.compile(r"-----BEGIN (?:[A-Z]+ )?PRIVATE KEY-----[A-Za-z0-9+/=\s]+-----END (?:[A-Z]+ )?PRIVATE KEY-----")),
    "eyj": ("jwt", re.compile(r"eyJ[A-Za-z0-9_-]+\.eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+")),
    "xoxb-": ("chat_token", re.compile(r"xoxb-[0-9]{10,13}-[0-9]{10,13}-[A-Za-z0-9]{24}")),
    "sk_live_": ("pay_key", re.compile(r"sk_live_[A-Za-z0-9]{24,}")),
    "aiza": ("cloud_key", re.compile(r"AIza[A-Za-z0-9_-]{35}(?![A-Za-z0-9_-])")),
    "glpat-": ("repo_token", re.compile(r"glpat-[A-Za-z0-9_-]{20}(?![A-Za-z0-9_-])")),
}
DIGITS_62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"
_FOLD = str.maketrans(UPPER, LOWER)


def base62(n: int, width: int) -> str:
    out = ""
    for _ in range(width):
        n, r = divmod(n, 62)
        out = DIGITS_62[r] + out
    return out


def crc_ok(token: str) -> bool:
    """The last six characters are the base-62 CRC-32 of the thirty before them."""
    body, check = token[4:-6], token[-6:]
    return base62(zlib.crc32(body.encode()), 6) == check


def jwt_ok(token: str) -> bool:
    """The first part decodes to a JSON object that names an algorithm."""
    head = token.split(".")[0]
    try:
        return "alg" in json.loads(base64.urlsafe_b64decode(head + "=" * (-len(head) % 4)))
    except (ValueError, binascii.Error, TypeError):
        return False


VALID = {"crc_token": crc_ok, "jwt": jwt_ok}


def build_automaton() -> ahocorasick.Automaton:
    a = ahocorasick.Automaton()
    for head in (*ASSIGN_HEADS, "akia", *EXTRA):
        a.add_word(head, head)
    a.make_automaton()
    return a


def scan(text: str, heads: ahocorasick.Automaton) -> list[tuple[str, int, int]]:
    """All spans of one text by start, then by kind in the order of KINDS."""
    low = text.lower()
    if len(low) != len(text):  # a letter that lowers to two characters would shift the offsets
        low = text.translate(_FOLD)
    starts = sorted({(end - len(head) + 1, head) for end, head in heads.iter(low)})
    spans, done = [], {}
    for start, head in starts:
        if head in EXTRA:
            kind, pattern = EXTRA[head]
        else:
            kind, pattern = ("access", ACCESS) if head == "akia" else ("assign", ASSIGN)
        if start < done.get(kind, 0):
            continue
        m = pattern.match(text, start)
        if not m:
            if kind == "jwt":  # whatever follows this run is the same for every head in it
                done[kind] = JWT_RUN.match(text, start).end() if text.startswith("eyJ", start) else start
            continue
        done[kind] = m.end()
        if kind == "assign" and len(m[2]) < 8 or kind == "access" and len(m[0]) < 16 or kind in VALID and not VALID[kind](m[0]):
            continue
        spans.append((kind, start, m.end()))
    spans += [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    rank = {k: i for i, k in enumerate(KINDS)}
    return sorted(spans, key=lambda s: (s[1], rank[s[0]]))


def scan_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, found array<struct<kind,start,end>>) of every row."""

    def start():
        heads = build_automaton()
        return lambda texts: {"found": [[{"kind": k, "start": a, "end": b} for k, a, b in scan(t, heads)] for t in texts]}

    return map_texts(docs, start, "found array<struct<kind:string,start:long,end:long>>", id_col, text_col)


def scan_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    def start():
        heads = build_automaton()
        show = lambda spans: ",".join(f"{k}:{a}:{b}" for k, a, b in spans)

        def work(texts):
            out = {"n_assign": [], "n_access": [], "n_hex": [], "base_sha256": [], "spans": []}
            for t in texts:
                spans = scan(t, heads)
                base = [s for s in spans if s[0] in ("assign", "access", "hex")]
                for kind in ("assign", "access", "hex"):
                    out[f"n_{kind}"].append(sum(s[0] == kind for s in base))
                out["base_sha256"].append(hashlib.sha256(show(base).encode()).hexdigest())
                out["spans"].append(show(spans))
            return out

        return work

    return map_texts(docs, start, "n_assign long, n_access long, n_hex long, base_sha256 string, spans string", id_col, text_col)


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_digests(table(spark, sf_dir, "documents").select("doc_id", "text"))
