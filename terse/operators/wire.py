"""Wire formats of coded vectors: symbols to bytes and back, for Arrow batches."""

from __future__ import annotations

from math import ceil, log2

import numpy as np


def _to_bytes(bits: np.ndarray) -> bytes:
    return np.packbits(bits.astype(np.uint8)).tobytes()


def _from_bytes(data: bytes) -> np.ndarray:
    return np.unpackbits(np.frombuffer(data, np.uint8))


class PrefixTernary:
    """0 as one bit, +1 and -1 as two: 1.5 bits an element when half of them are 0."""

    @staticmethod
    def pack(trits: np.ndarray) -> bytes:
        trits = np.asarray(trits, np.int8)
        width = 1 + (trits != 0)
        ends = np.cumsum(width)
        bits = np.zeros(int(ends[-1]) if len(ends) else 0, np.uint8)
        nz = trits != 0
        bits[(ends - width)[nz]] = 1
        bits[(ends - 1)[nz]] = trits[nz] < 0
        return _to_bytes(bits)

    @staticmethod
    def unpack(data: bytes, n: int) -> np.ndarray:
        bits = _from_bytes(data)
        out = np.zeros(n, np.int8)
        at = 0
        for i in range(n):
            if bits[at]:
                out[i] = -1 if bits[at + 1] else 1
                at += 2
            else:
                at += 1
        return out

    @staticmethod
    def bits(trits: np.ndarray) -> int:
        return len(trits) + int((np.asarray(trits) != 0).sum())


class Base3:
    """Five elements in a byte: 1.6 bits each, whatever they are."""

    WEIGHTS = np.array([81, 27, 9, 3, 1])

    @classmethod
    def pack(cls, trits: np.ndarray) -> bytes:
        padded = np.zeros(-(-len(trits) // 5) * 5, np.int64)
        padded[: len(trits)] = np.asarray(trits)
        return ((padded.reshape(-1, 5) + 1) @ cls.WEIGHTS).astype(np.uint8).tobytes()

    @classmethod
    def unpack(cls, data: bytes, n: int) -> np.ndarray:
        values = np.frombuffer(data, np.uint8).astype(np.int64)
        return ((values[:, None] // cls.WEIGHTS) % 3 - 1).reshape(-1)[:n].astype(np.int8)


class GapCode:
    """Distances between elements that are not 0 in a universal code of integers, each with a sign bit: cheap when most are 0."""

    @staticmethod
    def pack(trits: np.ndarray) -> bytes:
        places = np.flatnonzero(trits)
        gaps = np.diff(places, prepend=-1)
        out = [f"{len(places) + 1:b}"]
        out[0] = "0" * (len(out[0]) - 1) + out[0]
        for g, p in zip(gaps.tolist(), places.tolist(), strict=True):
            digits = f"{g:b}"
            out.append("0" * (len(digits) - 1) + digits + ("1" if trits[p] < 0 else "0"))
        return _to_bytes(np.frombuffer("".join(out).encode(), np.uint8) - 48)

    @staticmethod
    def unpack(data: bytes, n: int) -> np.ndarray:
        bits = _from_bytes(data).tolist()
        at = 0

        def number() -> int:
            nonlocal at
            zeros = 0
            while not bits[at]:
                zeros += 1
                at += 1
            value = 0
            for b in bits[at : at + zeros + 1]:
                value = 2 * value + b
            at += zeros + 1
            return value

        out, place = np.zeros(n, np.int8), -1
        for _ in range(number() - 1):
            place += number()
            out[place] = -1 if bits[at] else 1
            at += 1
        return out


class SparsePairs:
    """Index and 32-bit value of elements that are not 0."""

    @staticmethod
    def pack(v: np.ndarray) -> bytes:
        v = np.asarray(v, np.float32)
        places = np.flatnonzero(v)
        width = max(1, ceil(log2(max(2, len(v)))))
        bits = ((places[:, None] >> np.arange(width - 1, -1, -1)) & 1).reshape(-1)
        return len(places).to_bytes(4, "little") + v[places].astype("<f4").tobytes() + _to_bytes(bits)

    @staticmethod
    def unpack(data: bytes, n: int) -> np.ndarray:
        k = int.from_bytes(data[:4], "little")
        width = max(1, ceil(log2(max(2, n))))
        values = np.frombuffer(data, "<f4", k, 4)
        bits = _from_bytes(data[4 + 4 * k :])[: k * width].reshape(k, width)
        out = np.zeros(n)
        out[(bits.astype(np.int64) << np.arange(width - 1, -1, -1)).sum(1)] = values
        return out


class RawFloats:
    @staticmethod
    def pack(v: np.ndarray, bits: int = 32) -> bytes:
        return np.asarray(v).astype(f"<f{bits // 8}").tobytes()

    @staticmethod
    def unpack(data: bytes, n: int) -> np.ndarray:
        return np.frombuffer(data, f"<f{len(data) // max(n, 1)}" if n else "<f4").astype(float)


def pack_ternary(q: np.ndarray, block: int, coder=Base3) -> bytes:
    """A blockwise ternary vector: one 32-bit magnitude a block, then the symbols of all blocks."""
    q = np.asarray(q, float)
    scales = np.array([np.abs(q[i : i + block]).max() for i in range(0, len(q), block)], "<f4")
    return scales.tobytes() + coder.pack(np.sign(q).astype(np.int8))


def unpack_ternary(data: bytes, n: int, block: int, coder=Base3) -> np.ndarray:
    m = -(-n // block)
    scales = np.frombuffer(data, "<f4", m).astype(float)
    return coder.unpack(data[4 * m :], n) * np.repeat(scales, block)[:n]
