"""Words over A, C, G, T as numbers: packing, reverse complements, text projection, and a portable mixer.

Codes: A=0, C=1, G=2, T=3, the first base most significant, so numeric order is lexicographic order.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

# Accented letters of the four languages, and what they become.
ACCENTED = "áàâäãéèêëíìîïóòôöõúùûüñç"
PLAIN = "aaaaaeeeeiiiiooooouuuunc"
LETTERS = "abcdefghijklmnopqrstuvwxyz"
BASES = "ACGTACGTACGTACGTACGTACGTAC"
JUNK = "!%*&$|#"

MAX_K = 32
_CODE = np.full(256, 255, dtype=np.uint8)
for _i, _b in enumerate(b"ACGT"):
    _CODE[_b] = _CODE[_b + 32] = _i


def _check_k(k: int) -> None:
    if not 1 <= k <= MAX_K:
        raise ValueError(f"a packed word has 1 to {MAX_K} bases, not {k}; longer ones need hash_kmers(hash='cyclic')")


# -- columns -------------------------------------------------------------------------------------------------------


def project_text(text: Column, junk: str = "drop") -> Column:
    """A text as bases: lower case, accents folded, letters by index modulo 4, all else dropped (or junk marks as N)."""
    plain = F.translate(F.lower(text), ACCENTED, PLAIN)
    if junk == "N":
        plain = F.regexp_replace(F.translate(plain, JUNK, "N" * len(JUNK)), "[^a-zN]", "")
    elif junk == "drop":
        plain = F.regexp_replace(plain, "[^a-z]", "")
    else:
        raise ValueError("junk is 'drop' or 'N'")
    return F.translate(plain, LETTERS, BASES)


def reverse_complement(word: Column) -> Column:
    return F.reverse(F.translate(word, "ACGT", "TGCA"))


def canonical(word: Column, stranded: bool = False) -> Column:
    """The lesser of a word and its reverse complement; the word itself if strands are told apart."""
    return word if stranded else F.least(word, reverse_complement(word))


def encode_kmer(word: Column, k: int) -> Column:
    """A word's packed code as a long (for 32 bases the bit pattern of the unsigned number)."""
    _check_k(k)
    digits = F.conv(F.translate(word, "ACGT", "0123"), 4, 10)
    if k < MAX_K:
        return digits.cast("long")
    wide = digits.cast("decimal(20,0)")
    over = F.lit(str(2**64)).cast("decimal(20,0)")
    return F.when(wide * 2 >= over, wide - over).otherwise(wide).cast("long")


def decode_kmer(code: Column, k: int) -> Column:
    """The word of a code."""
    _check_k(k)
    three = F.lit(3).cast("long")
    letters = [F.substr(F.lit("ACGT"), (F.shiftrightunsigned(code, 2 * (k - 1 - i)).bitwiseAND(three) + 1).cast("int"), F.lit(1)) for i in range(k)]
    return F.concat(*letters)


def unsigned_mod(code: Column, prime: int, k: int = MAX_K) -> Column:
    """The unsigned number modulo a prime; a plain remainder where the code is never negative."""
    p = F.lit(int(prime)).cast("long")
    if k < MAX_K:
        return code % p
    return ((F.shiftrightunsigned(code, 1) % p) * 2 + code.bitwiseAND(F.lit(1).cast("long"))) % p


def mixer(tag: str, *args: Column, seed: int = 42) -> Column:
    """60 well-mixed bits of the arguments, the same number in other engines: the head of an md5 digest."""
    text = F.concat_ws("|", F.lit(tag), F.lit(str(seed)), *(a.cast("string") for a in args))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


# -- kernels -------------------------------------------------------------------------------------------------------


_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _left(x: np.ndarray, by: int) -> np.ndarray:
    return (x << np.uint64(by)) | (x >> np.uint64(64 - by))


def _finish(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(33))) * _P2
    x = (x ^ (x >> np.uint64(29))) * _P3
    return x ^ (x >> np.uint64(32))


def xxhash64_of(codes: np.ndarray, number: int | None = None) -> np.ndarray:
    """The engine's xxhash64 of longs, or of longs followed by a small whole number, as signed longs."""
    with np.errstate(over="ignore"):
        x = np.uint64(42) + _P5 + np.uint64(8)
        x = _left(x ^ (_left(codes.view(np.uint64) * _P2, 31) * _P1), 27) * _P1 + _P4
        x = _finish(x)
        if number is not None:
            x = _finish(_left((x + _P5 + np.uint64(4)) ^ (np.uint64(number) * _P1), 23) * _P2 + _P3)
    return x.view(np.int64)


def _projection(junk: str) -> tuple[np.ndarray, np.ndarray]:
    """What a byte becomes, and what the byte after 0xC3 (an accented letter) becomes; 0 for nothing."""
    base = dict(zip(LETTERS, BASES.encode(), strict=True))
    one, two = np.zeros(256, np.uint8), np.zeros(256, np.uint8)
    for c, b in base.items():
        one[ord(c)] = one[ord(c.upper())] = b
    for accented, c in zip(ACCENTED, PLAIN, strict=True):
        two[accented.encode()[1]] = two[accented.upper().encode()[1]] = base[c]
    if junk == "N":
        one[list(JUNK.encode())] = ord("N")
    elif junk != "drop":
        raise ValueError("junk is 'drop' or 'N'")
    return one, two


def project_bytes(raw: np.ndarray, ends: np.ndarray, junk: str = "drop") -> tuple[np.ndarray, np.ndarray]:
    """`project_text` for UTF-8 texts end to end: their bases end to end, and where each text's end.

    Two more letters have a plain one as their lower case: the dotted capital I and the Kelvin sign.
    """
    one, two = _projection(junk)
    out = one[raw]
    at = np.flatnonzero(raw[:-1] == 0xC3)
    out[at] = two[raw[at + 1]]
    at = np.flatnonzero(raw[:-1] == 0xC4)
    out[at[raw[at + 1] == 0xB0]] = one[ord("i")]
    at = np.flatnonzero(raw[:-2] == 0xE2)
    out[at[(raw[at + 1] == 0x84) & (raw[at + 2] == 0xAA)]] = one[ord("k")]
    keep = out != 0
    return out[keep], np.concatenate([[0], np.cumsum(keep)])[ends]


def base_codes(raw: np.ndarray) -> np.ndarray:
    """Codes of letters; 255 for what is no base."""
    return _CODE[raw]


def pack_windows(codes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Forward and reverse-complement codes of every window of k bases, by doubling; windows with no base are junk."""
    _check_k(k)
    fwd = (codes & 3).astype(np.uint64)
    rev = np.uint64(3) - fwd
    parts, have, width = [], 1, k
    while True:
        if width & have:
            parts.append((have, fwd, rev))
        if 2 * have > k:
            break
        shift = np.uint64(2 * have)
        fwd, rev = (fwd[:-have] << shift) | fwd[have:], rev[:-have] | (rev[have:] << shift)
        have *= 2
    n = max(0, len(codes) - k + 1)
    out_f, out_r, at = np.zeros(n, np.uint64), np.zeros(n, np.uint64), 0
    for size, f, r in reversed(parts):
        out_f = (out_f << np.uint64(2 * size) if at else out_f) | f[at : at + n]
        out_r |= r[at : at + n] << np.uint64(2 * at)
        at += size
    return out_f, out_r


def windows_of(raw: np.ndarray, ends: np.ndarray, k: int, stranded: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Valid windows of reads laid end to end: read index, position, code (canonical unless stranded).

    A window that crosses a read's end or holds a letter other than A, C, G, T gives nothing.
    """
    codes = base_codes(raw)
    if len(codes) < k:
        none = np.zeros(0, np.int64)
        return none, none, np.zeros(0, np.uint64)
    fwd, rev = pack_windows(codes, k)
    bad = np.concatenate([[0], np.cumsum(codes == 255, dtype=np.int32)])
    sizes = np.diff(ends, prepend=0)
    read = np.repeat(np.arange(len(ends)), sizes)[: len(fwd)]
    at = np.flatnonzero((bad[k:] == bad[:-k]) & (np.arange(len(fwd)) + k <= ends[read]))
    read = read[at]
    code = fwd[at] if stranded else np.minimum(fwd[at], rev[at])
    return read, at - (ends - sizes)[read], code


def reverse_complement_codes(codes: np.ndarray, k: int) -> np.ndarray:
    x, out = codes.astype(np.uint64), np.zeros(len(codes), np.uint64)
    for _ in range(k):
        out = (out << np.uint64(2)) | (np.uint64(3) - (x & np.uint64(3)))
        x = x >> np.uint64(2)
    return out


def decode_codes(codes: np.ndarray, k: int) -> list[str]:
    shifts = np.arange(2 * (k - 1), -1, -2, dtype=np.uint64)
    letters = np.frombuffer(b"ACGT", np.uint8)[((codes.astype(np.uint64)[:, None] >> shifts) & np.uint64(3)).astype(np.int64)]
    return [x.tobytes().decode() for x in letters]


def cyclic_hashes(raw: np.ndarray, k: int, stranded: bool = False) -> np.ndarray:
    """64-bit cyclic hash of every window of any length, the same for both strands unless stranded.

    Letter hashes are rotated by their distance to the window's end and XORed; the sum over a window follows from
    running XORs of rotated letters, so the cost per base does not depend on k.
    """
    seeds = np.array([0x3C8BFBB395C60474, 0x3193C18562A02B4C, 0x20323ED082572324, 0x295549F54BE24456, 0], np.uint64)
    codes = base_codes(raw)
    n = len(codes) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint64)

    def rolled(values: np.ndarray) -> np.ndarray:
        # Undo the rotation of place i, XOR up, and rotate the difference for the window's end.
        i = np.arange(len(values), dtype=np.uint64)
        total = np.concatenate([[np.uint64(0)], np.bitwise_xor.accumulate(_rotate(values, (64 - i % 64) % 64))])
        return _rotate(total[k:] ^ total[:-k], (np.arange(n, dtype=np.uint64) + np.uint64(k - 1)) % np.uint64(64))

    at = np.where(codes == 255, 4, codes)
    fwd = rolled(seeds[at])
    if stranded:
        return fwd
    back = rolled(seeds[np.where(codes == 255, 4, 3 - (at & 3))][::-1])[::-1]
    return np.minimum(fwd, back)


def _rotate(x: np.ndarray, by: np.ndarray) -> np.ndarray:
    by = np.asarray(by, np.uint64)
    return (x << by) | (x >> ((np.uint64(64) - by) % np.uint64(64)))
