"""Keyed hashing without leaving the JVM.

HMAC-SHA256 needs the key's 64 bytes exclusive-or'ed with 0x36 and 0x5c.  For a literal key these are computed once, on the
driver; for a key column in hexadecimal, 32 bits at a time.  Keys may have any characters and any length: one of over 64
bytes is hashed first, as the standard says.  Keys that are put together of several parts have SEPARATOR between them.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

BLOCK = 64
INNER, OUTER = 0x36, 0x5C
SEPARATOR = "|"
SLICES = 16
LETTERS = "ghijklmnopqrstuv"


def check_key(key: str) -> str:
    if not key:
        raise ValueError("an owner's key must not be empty")
    return key


def pads(key: str) -> tuple[bytes, bytes]:
    """The inner and the outer block of a key."""
    raw = check_key(key).encode()
    raw = (hashlib.sha256(raw).digest() if len(raw) > BLOCK else raw).ljust(BLOCK, b"\0")
    return bytes(x ^ INNER for x in raw), bytes(x ^ OUTER for x in raw)


def _padded(key: Column) -> Column:
    """The key's block as 128 hex digits."""
    raw = key.cast("binary")
    return F.rpad(F.when(F.octet_length(raw) > BLOCK, F.sha2(raw, 256)).otherwise(F.hex(raw)), 2 * BLOCK, "0")


def _xored(block: Column, byte: int) -> Column:
    word = int(f"{byte:02x}" * 4, 16)
    each = (F.conv(F.substring(block, 1 + 8 * i, 8), 16, 10).cast("long").bitwiseXOR(F.lit(word)) for i in range(BLOCK // 4))
    return F.unhex(F.concat(*(F.lpad(F.hex(x), 8, "0") for x in each)))


def composed(*parts: Column | str) -> Column:
    """A key of several parts; no two lists of parts without SEPARATOR give the same."""
    return F.concat_ws(SEPARATOR, *(F.lit(p) if isinstance(p, str) else p for p in parts))


def hmac_sha256(message: Column, key: Column | str) -> Column:
    """Hex digest of HMAC-SHA256."""
    digest = lambda inner, outer: F.sha2(F.concat(outer, F.unhex(F.sha2(F.concat(inner, message.cast("binary")), 256))), 256)
    if isinstance(key, str):
        return digest(*(F.lit(bytearray(p)) for p in pads(key)))
    blocks = lambda b: F.struct(_xored(b, INNER).alias("inner"), _xored(b, OUTER).alias("outer"))
    return let(let(_padded(key), blocks), lambda b: digest(b["inner"], b["outer"]))


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is computed once, also where ``use`` has it inside another lambda."""
    return F.transform(F.array(value), use)[0]


def positions(seed: Column, h: Column | int, m: Column | int, family: str = "random", most: int = 48) -> Column:
    """``h`` pseudo-random positions below ``m`` from a hex seed.

    ``random``: 16-bit slices of SHA-256 in counter mode (without bias for an m that divides 65536).  ``double``: a + i b mod
    m of two 32-bit slices with an odd b.  ``most`` bounds ``h`` where that is a column.
    """
    h, m = (F.lit(x) if isinstance(x, int) else x for x in (h, m))
    if family == "double":
        part = lambda s, k: F.conv(F.substring(s, 1 + 8 * k, 8), 16, 10).cast("long")
        walk = lambda ab: F.transform(F.sequence(F.lit(0), h - 1), lambda i: ((ab["a"] + i * ab["b"]) % m).cast("int"))
        return let(seed, lambda s: let(F.struct(part(s, 0).alias("a"), ((part(s, 1) * 2 + 1) % m).alias("b")), walk))
    blocks = (most + SLICES - 1) // SLICES
    slices = lambda d: F.transform(
        F.sequence(F.lit(0), h - 1), lambda i: (F.conv(F.substr(d, 1 + 4 * i, F.lit(4)), 16, 10).cast("long") % m).cast("int")
    )
    stream = lambda s: F.concat(*(F.sha2(F.concat(s, F.lit(f"|{k}")).cast("binary"), 256) for k in range(blocks)))
    return let(let(seed, stream), slices)


def letters(hex_digits: Column) -> Column:
    """Hex digits as the letters g to v, fit for a key."""
    return F.translate(hex_digits, "0123456789abcdef", LETTERS)


def uniforms(key: Column, tags: Sequence[str]) -> Column:
    """An array of ``uniform`` for several tags."""
    prefix = key.cast("string")
    digest = lambda tag: F.md5(F.concat(prefix, F.lit("|"), tag).cast("binary"))
    return F.transform(F.array(*map(F.lit, tags)), lambda tag: F.conv(F.substring(digest(tag), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0))


def uniform(key: Column, tag: str) -> Column:
    """A number in [0, 1) from an id and a tag, the same in every engine: 32 bits of an MD5."""
    digest = F.md5(F.concat(key.cast("string"), F.lit(f"|{tag}")).cast("binary"))
    return F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)
