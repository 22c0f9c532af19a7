"""The coin of ticks.py for arrays: md5 over many messages at once that differ in one number, for work inside one task."""

from __future__ import annotations

from hashlib import md5

import numpy as np

# fixed values: the constants, turns and places of md5
SINES = (np.abs(np.sin(np.arange(1, 65))) * 2.0**32).astype(np.uint64).astype(np.uint32)
TURNS = [t for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for t in four * 4]
PLACES = [*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *((7 * i) % 16 for i in range(16))]
START = tuple(np.uint32(x) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
FEW = 400  # fewer messages, and those that may be long, are taken one by one
AT_ONCE = 16384  # messages whose words stay near the processor


def _heads(words: list, n: int) -> np.ndarray:
    """The first 32 bits of the digests of n one-block messages; each of the 16 words is a number or an array."""
    a, b, c, d = (np.full(n, x) for x in START)
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, f)
            np.bitwise_and(f, b, f)
            np.bitwise_xor(f, d, f)
        elif i < 32:
            np.bitwise_xor(b, c, f)
            np.bitwise_and(f, d, f)
            np.bitwise_xor(f, c, f)
        elif i < 48:
            np.bitwise_xor(b, c, f)
            np.bitwise_xor(f, d, f)
        else:
            np.invert(d, f)
            np.bitwise_or(f, b, f)
            np.bitwise_xor(f, c, f)
        word = words[PLACES[i]]
        f += a
        if isinstance(word, np.ndarray):
            f += word
            f += SINES[i]
        else:
            f += np.uint32((int(word) + int(SINES[i])) & 0xFFFFFFFF)
        np.right_shift(f, np.uint32(32 - TURNS[i]), g)
        np.left_shift(f, np.uint32(TURNS[i]), f)
        np.bitwise_or(f, g, f)
        f += b
        a, b, c, d, f = d, f, b, c, a
    a += START[0]
    return a.byteswap()


class Field:
    """Numbers, in ascending order and not negative, that stand as text in one place of messages."""

    def __init__(self, numbers: np.ndarray):
        self.numbers = np.asarray(numbers, np.int64)
        if len(self.numbers) and (self.numbers[0] < 0 or (np.diff(self.numbers) < 0).any()):
            raise ValueError("numbers in ascending order, from 0 on")
        self.groups, self.placed = [], {}
        edges = np.searchsorted(self.numbers, [0, *(10**k for k in range(1, 19))], "left")
        edges = [0, *edges[1:].tolist(), len(self.numbers)]
        for digits, (i, j) in enumerate(zip(edges, edges[1:], strict=False), 1):
            if j > i:
                self.groups.append((i, j, digits))

    def _words(self, at: int, group: tuple[int, int, int]) -> np.ndarray:
        """The digits of a group as little-endian words, after `at` empty bytes."""
        if (at, group) not in self.placed:
            i, j, digits = group
            text = np.zeros((j - i, -(-(at + digits) // 4) * 4), np.uint8)
            left = self.numbers[i:j].copy()
            for k in range(at + digits - 1, at - 1, -1):
                left, text[:, k] = np.divmod(left, 10)
            text[:, at : at + digits] += 48
            self.placed[at, group] = np.ascontiguousarray(text.view("<u4").T)
        return self.placed[at, group]

    def coins(self, before: str, after: str = "", low: int = 0, high: int | None = None) -> np.ndarray:
        """md5(before || number || after) as the coin takes it, for numbers low to high - 1 by place."""
        high = len(self.numbers) if high is None else high
        out, head, tail = np.empty(max(0, high - low), np.uint32), before.encode(), after.encode()
        if len(out) < FEW or len(head) + len(tail) > 55 - 19:
            return np.array([int.from_bytes(md5(b"%b%d%b" % (head, i, tail)).digest()[:4], "big") for i in self.numbers[low:high].tolist()], np.uint32)
        for group in self.groups:
            i, j, digits = group
            size = len(head) + digits + len(tail)
            whole = np.frombuffer((head + bytes(digits) + tail + b"\x80").ljust(56, b"\0") + (8 * size).to_bytes(8, "little"), "<u4")
            first = len(head) // 4
            for k in range(max(i, low), min(j, high), AT_ONCE):
                end = min(j, high, k + AT_ONCE)
                words = whole.tolist()
                for w, column in enumerate(self._words(len(head) % 4, group)[:, k - i : end - i], first):
                    words[w] = column | whole[w]
                out[k - low : end - low] = _heads(words, end - k)
        return out


FOURS = np.frombuffer("".join(f"{i:04d}" for i in range(10_000)).encode(), np.uint8).reshape(-1, 4)
TENS = np.array([10**k for k in range(1, 19)], np.int64)


def coins_of(*parts: str | np.ndarray) -> np.ndarray:
    """md5 of messages as the coin takes it; a part is text that all messages share, or an array of numbers that are not negative."""
    at = [k for k, p in enumerate(parts) if not isinstance(p, str)]
    numbers = [np.ascontiguousarray(x, np.int64) for x in np.broadcast_arrays(*(parts[k] for k in at))]
    out = np.empty(len(numbers[0]), np.uint32)
    if any((x < 0).any() for x in numbers):
        raise ValueError("numbers from 0 on")
    shared = sum(len(p.encode()) for p in parts if isinstance(p, str))
    if len(out) < FEW or shared + 19 * len(at) > 55 and shared + sum(len(str(int(x.max()))) for x in numbers) > 55:
        text = "".join(p.replace("%", "%%") if isinstance(p, str) else "%d" for p in parts)
        return np.array([int.from_bytes(md5((text % row).encode()).digest()[:4], "big") for row in zip(*(x.tolist() for x in numbers), strict=True)], np.uint32)
    digits = [np.searchsorted(TENS, x, "right") + 1 for x in numbers]
    shape = np.zeros(len(out), np.int64)
    for d in digits:
        shape = shape * 20 + d
    order = None if (shape == shape[0]).all() else np.argsort(shape, kind="stable")
    edges = [0, len(out)] if order is None else [0, *(np.nonzero(np.diff(shape[order]))[0] + 1).tolist(), len(out)]
    for first, end in zip(edges, edges[1:], strict=False):
        for low in range(first, end, AT_ONCE):
            high = min(end, low + AT_ONCE)
            rows = slice(low, high) if order is None else order[low:high]
            text, place, which = np.zeros((high - low, 64), np.uint8), 0, iter(zip(numbers, digits, strict=True))
            for p in parts:
                if isinstance(p, str):
                    text[:, place : place + len(p.encode())] = np.frombuffer(p.encode(), np.uint8)
                    place += len(p.encode())
                    continue
                x, d = next(which)
                left, long = x[rows], int(d[rows][0])
                for right in range(place + long, place, -4):
                    width = min(4, right - place)
                    left, four = np.divmod(left, 10_000) if right - place > 4 else (left, left)
                    text[:, right - width : right] = FOURS[four, 4 - width :]
                place += long
            text[:, place] = 0x80
            text[:, 56:] = np.frombuffer((8 * place).to_bytes(8, "little"), np.uint8)
            words, filled = text.view("<u4"), -(-(place + 1) // 4)
            out[rows] = _heads([np.ascontiguousarray(words[:, k]) if k < filled else words[0, k] for k in range(16)], high - low)
    return out
