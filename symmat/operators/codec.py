"""Physical encodings of a block's final string and rules.

``stream``: no rules, 32-bit symbols. ``g32``: 32-bit integers. ``gpack``: every integer at width 1 + floor(log2 of the
largest id). ``gans``: rules packed as before, final string by an entropy coder of the asymmetric-numeral kind in its range
form over a folded alphabet; many coder states run side by side so that each step is a vector operation. A string that is
shorter packed stays packed, so ``gans`` is never larger than ``gpack`` by more than a byte a block.
"""

from __future__ import annotations

import numpy as np

from .kernel import Grammar, from_marked

NAMES = ("stream", "g32", "gpack", "gans")
#: Alphabet folding: symbols from 2**(FOLD + 7) on shed low bytes.
FOLD = 1
_P, _LOW = 15, 1 << 16


def width_of(largest: int) -> int:
    return max(1, int(largest).bit_length())


def pack(values: np.ndarray, width: int) -> bytes:
    """Little-endian bit string: value i at bits [i * width, (i + 1) * width)."""
    if not len(values):
        return b""
    bits = np.unpackbits(values.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")[:, :width] if len(values) < 1 << 16 else None
    if bits is not None:
        return np.packbits(bits.ravel(), bitorder="little").tobytes()
    # whole groups of 8 values fill whole bytes, so long arrays are packed piece by piece
    step = 1 << 15
    return b"".join(pack(values[i : i + step], width) for i in range(0, len(values), step))


def unpack(data: bytes, width: int, count: int, first: int = 0) -> np.ndarray:
    """Values first .. first + count: two shifted 64-bit words each, so any range can be read alone."""
    if not count:
        return np.zeros(0, np.int64)
    raw = np.frombuffer(data + b"\0" * 16, np.uint8)
    bit = (np.arange(first, first + count, dtype=np.int64)) * width
    byte, shift = bit >> 3, (bit & 7).astype(np.uint64)
    word = np.zeros(count, np.uint64)
    for k in range(8):
        word |= raw[byte + k].astype(np.uint64) << np.uint64(8 * k)
    low = word >> shift
    high = np.where(shift > 0, raw[byte + 8].astype(np.uint64) << (np.uint64(64) - np.maximum(shift, np.uint64(1))), np.uint64(0))
    mask = np.uint64((1 << width) - 1)
    return ((low | high) & mask).astype(np.int64)


def fold(symbols: np.ndarray, by: int = FOLD) -> tuple[np.ndarray, bytes]:
    """Small-alphabet symbols, and the bytes that large ones shed (lowest first, symbol after symbol)."""
    f = 1 << (by + 7)
    s, offset = symbols.astype(np.int64).copy(), np.zeros(len(symbols), np.int64)
    shed = np.zeros((len(s), 8), np.uint8)
    depth = np.zeros(len(s), np.int64)
    while (big := s >= f).any():
        shed[big, depth[big]] = s[big] & 255
        s[big] >>= 8
        offset[big] += f - f // 256
        depth[big] += 1
    return s + offset, shed[np.arange(8)[None] < depth[:, None]].tobytes()


def unfold(folded: np.ndarray, shed: bytes, by: int = FOLD) -> np.ndarray:
    f = 1 << (by + 7)
    step = f - f // 256
    depth = np.where(folded < f, 0, (folded - f) // step + 1)
    s = folded - depth * step
    raw = np.frombuffer(shed, np.uint8)
    at = np.cumsum(depth) - depth
    for k in range(int(depth.max()) if len(depth) else 0, 0, -1):
        some = depth >= k
        s[some] = (s[some] << 8) | raw[at[some] + k - 1]
    return s


def _table(counts: np.ndarray) -> np.ndarray:
    """Frequencies of sum 2**_P, at least 1 for each symbol that occurs."""
    total, size = int(counts.sum()), 1 << _P
    f = np.where(counts > 0, np.maximum(1, counts * size // max(1, total)), 0).astype(np.int64)
    while (gap := size - int(f.sum())) != 0:
        big = np.argsort(-f, kind="stable")
        if gap > 0:
            f[big[0]] += gap
        else:
            room = big[f[big] > 1]
            cut = min(-gap, max(1, int(f[room[0]]) // 2))
            f[room[0]] -= cut
    return f


def _gamma(values: np.ndarray) -> np.ndarray:
    """Bits of the values (1 or more), each as so many zeros as it has binary digits behind the first, then the digits."""
    digits = np.frexp(values.astype(float))[1].astype(np.int64)
    width = 2 * digits - 1
    first = np.cumsum(width) - width
    at = np.arange(int(width.sum())) - np.repeat(first, width)
    down = np.repeat(width, width) - 1 - at
    return np.where(down < np.repeat(digits, width), np.repeat(values, width) >> np.minimum(down, 62), 0).astype(np.uint8) & 1


def _from_gamma(bits: np.ndarray, count: int) -> np.ndarray:
    out, at = np.empty(count, np.int64), 0
    ones = np.flatnonzero(bits)
    for k in range(count):
        one = int(ones[np.searchsorted(ones, at)])
        more = one - at
        out[k] = int("".join(map(str, bits[one : one + more + 1].tolist())), 2)
        at = one + more + 1
    return out


def ans_encode(symbols: np.ndarray, by: int = FOLD) -> bytes:
    """Head, bytes shed by folding, coder words, last states, and the table: gaps between used symbols and their frequencies, in variable length."""
    folded, shed = fold(symbols, by)
    n = len(folded)
    if not n:
        return np.array([0, 0, 0, 0, 0], "<u4").tobytes()
    counts = np.bincount(folded)
    freq = _table(counts)
    start = np.cumsum(freq) - freq
    lanes = int(np.clip(n // 2048, 1, 256))
    state = np.full(lanes, _LOW, np.uint64)
    steps = -(-n // lanes)
    words = [np.zeros(0, np.uint16)] * steps
    for t in range(steps - 1, -1, -1):
        s = folded[t * lanes : (t + 1) * lanes]
        f, c, x = freq[s].astype(np.uint64), start[s].astype(np.uint64), state[: len(s)]
        over = x >= f << np.uint64(32 - _P)
        words[t] = (x[over] & np.uint64(0xFFFF)).astype(np.uint16)
        x = np.where(over, x >> np.uint64(16), x)
        state[: len(s)] = (x // f << np.uint64(_P)) + x % f + c
    body = np.concatenate(words).astype("<u2").tobytes()
    seen = np.flatnonzero(freq)
    table = np.packbits(np.concatenate([_gamma(np.diff(seen, prepend=-1)), _gamma(freq[seen])]), bitorder="little").tobytes()
    head = np.array([n, len(seen), len(shed), lanes, len(body)], "<u4").tobytes()
    return head + shed + body + state.astype("<u4").tobytes() + table


def ans_decode(data: bytes, by: int = FOLD) -> np.ndarray:
    n, used, n_shed, lanes, n_body = np.frombuffer(data, "<u4", 5).tolist()
    if not n:
        return np.zeros(0, np.int64)
    shed, at = data[20 : 20 + n_shed], 20 + n_shed
    words = np.frombuffer(data, "<u2", n_body // 2, at).astype(np.uint64)
    state = np.frombuffer(data, "<u4", lanes, at + n_body).astype(np.uint64)
    coded = _from_gamma(np.unpackbits(np.frombuffer(data, np.uint8, -1, at + n_body + 4 * lanes), bitorder="little"), 2 * used)
    seen = np.cumsum(coded[:used]) - 1
    freq = np.zeros(int(seen[-1]) + 1, np.int64)
    freq[seen] = coded[used:]
    start = np.cumsum(freq) - freq
    slot = np.repeat(np.arange(len(freq)), freq)
    out, low, w = np.empty(n, np.int64), np.uint64((1 << _P) - 1), 0
    fu, su = freq.astype(np.uint64), start.astype(np.uint64)
    for t in range(-(-n // lanes)):
        k = min(lanes, n - t * lanes)
        x = state[:k]
        s = slot[x & low]
        out[t * lanes : t * lanes + k] = s
        x = fu[s] * (x >> np.uint64(_P)) + (x & low) - su[s]
        need = x < np.uint64(_LOW)
        got = int(need.sum())
        x[need] = (x[need] << np.uint64(16)) | words[w : w + got]
        w += got
        state[:k] = x
    return unfold(out, shed, by)


def encode(g: Grammar, name: str, by: int = FOLD) -> tuple[bytes, bytes, int]:
    """Bytes of the final string, bytes of the rules, and the width of packed integers."""
    width = width_of(g.n_max)
    c, r = g.marked(), g.rules.ravel()
    if name in ("stream", "g32"):
        if g.n_max >= 1 << 32:
            raise ValueError(f"{name} holds ids below 2**32; the largest is {g.n_max}")
        if name == "stream" and len(r):
            raise ValueError("stream has no rules")
        return c.astype("<u4").tobytes(), r.astype("<u4").tobytes(), 32
    if name == "gpack":
        return pack(c, width), pack(r, width), width
    if name == "gans":
        coded, packed = ans_encode(c, by), pack(c, width)
        # a short string may be smaller packed than with its table of frequencies; the last byte says which it is
        return (coded + b"\1" if len(coded) < len(packed) else packed + b"\0"), pack(r, width), width
    raise ValueError(f"unknown codec {name}")


def decode(name: str, c: bytes, r: bytes, width: int, c_len: int, r_len: int, space: int, by: int = FOLD) -> Grammar:
    if name in ("stream", "g32"):
        marked, rules = np.frombuffer(c, "<u4").astype(np.int64), np.frombuffer(r, "<u4").astype(np.int64)
    else:
        coded = name == "gans" and c[-1:] == b"\1"
        marked = ans_decode(c[:-1], by) if coded else unpack(c, width, c_len)
        rules = unpack(r, width, 2 * r_len)
    return from_marked(marked, rules.reshape(-1, 2), space)
