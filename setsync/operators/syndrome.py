"""Syndrome sketch: odd power sums over GF(2^w); as many as the differences it can decode.

Both sides' sums XOR to those of the difference. Even sums are squares; Berlekamp-Massey finds the
locator, and its roots, split apart by traces, are the digests. A sketch that is too small shows as a
locator without as many roots as its degree, never as a wrong answer.
"""

from __future__ import annotations

import random
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setsync.operators.transfer import payload_lines
from setsync.plans import ledger
from setsync.plans.costs import DIGEST_BYTES
from setsync.sources.messages import settled, spread

#: Low terms of the field polynomials by width.
FIELD = {16: 0x2B, 32: 0x8D, 64: 0x1B}


class Field:
    def __init__(self, width: int = 64):
        self.w, self.low, self.mask = width, FIELD[width], (1 << width) - 1

    def mul(self, a: int, b: int) -> int:
        if not a or not b:
            return 0
        table = [0] * 16
        for k in range(1, 16):
            table[k] = table[k >> 1] << 1 ^ (a if k & 1 else 0)
        r = 0
        for s in range(self.w - 4, -1, -4):
            r = r << 4 ^ table[b >> s & 15]
        return self.reduce(r)

    def reduce(self, r: int) -> int:
        while r >> self.w:
            high, r = r >> self.w, r & self.mask
            low, k = self.low, 0
            while low:
                if low & 1:
                    r ^= high << k
                low, k = low >> 1, k + 1
        return r

    def inverse(self, a: int) -> int:
        out, power = 1, a
        for _ in range(self.w - 1):
            power = self.mul(power, power)
            out = self.mul(out, power)
        return out

    def mul_np(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        a, b, r = a.copy(), b.copy(), np.zeros_like(a)
        top, one, low, mask = np.uint64(self.w - 1), np.uint64(1), np.uint64(self.low), np.uint64(self.mask)
        for _ in range(self.w):
            r ^= a * (b & one)
            carry = (a >> top) & one
            a = ((a << one) & mask) ^ (carry * low)
            b >>= one
        return r

    # Polynomials: coefficient lists, lowest first, no zero at the end.
    def trim(self, p: list[int]) -> list[int]:
        while p and not p[-1]:
            p.pop()
        return p

    def mod(self, p: list[int], f: list[int]) -> list[int]:
        p, lead = p[:], self.inverse(f[-1])
        while len(p) >= len(f):
            if p[-1]:
                q = self.mul(p[-1], lead)
                at = len(p) - len(f)
                for k, c in enumerate(f):
                    p[at + k] ^= self.mul(q, c)
            p.pop()
        return self.trim(p)

    def gcd(self, a: list[int], b: list[int]) -> list[int]:
        while b:
            a, b = b, self.mod(a, b)
        lead = self.inverse(a[-1])
        return [self.mul(c, lead) for c in a]

    def divide(self, p: list[int], f: list[int]) -> list[int]:
        p, out, lead = p[:], [0] * (len(p) - len(f) + 1), self.inverse(f[-1])
        for at in range(len(out) - 1, -1, -1):
            q = out[at] = self.mul(p[at + len(f) - 1], lead)
            for k, c in enumerate(f):
                p[at + k] ^= self.mul(q, c)
        return self.trim(out)

    def squarer(self, f: list[int]):
        """p -> p^2 mod f, through the even powers of x mod f."""
        powers, power = [], [1]
        for k in range(len(f) - 1):
            powers.append(power)
            power = self.mod([0, 0, *power], f)

        def square(p: list[int]) -> list[int]:
            out = [0] * (len(f) - 1)
            for c, base in zip(p, powers):
                c = self.mul(c, c)
                if c:
                    for k, b in enumerate(base):
                        out[k] ^= self.mul(c, b)
            return self.trim(out)

        return square

    def roots(self, f: list[int], rng: random.Random) -> list[int] | None:
        """All roots of a monic f if it splits into distinct linear factors, else None."""
        if len(f) <= 1:
            return []
        square, power = self.squarer(f), self.mod([0, 1], f)
        for _ in range(self.w):
            power = square(power)
        if power != self.mod([0, 1], f):
            return None
        out, work = [], [f]
        while work:
            g = work.pop()
            if len(g) == 2:
                out.append(self.mul(g[0], self.inverse(g[1])))
                continue
            square = self.squarer(g)
            while True:
                term = self.mod([0, rng.getrandbits(self.w) | 1], g)
                trace = term[:]
                for _ in range(self.w - 1):
                    term = square(term)
                    size = max(len(trace), len(term))
                    trace = [(trace[k] if k < len(trace) else 0) ^ (term[k] if k < len(term) else 0) for k in range(size)]
                trace = self.trim(trace)
                part = self.gcd(g, trace) if trace else g
                if 1 < len(part) < len(g):
                    work += [part, self.divide(g, part)]
                    break
        return out


def sketch(digests: np.ndarray, capacity: int, width: int = 64) -> list[int]:
    """The odd power sums x, x^3, ... of the digests' low ``width`` bits."""
    field = Field(width)
    x = digests.astype(np.int64).view(np.uint64) & np.uint64(field.mask)
    square, power, out = field.mul_np(x, x), x, []
    for _ in range(capacity):
        out.append(int(np.bitwise_xor.reduce(power)) if len(power) else 0)
        power = field.mul_np(power, square)
    return out


def locator(sums: list[int], field) -> list[int] | None:
    """The polynomial whose roots are the inverses of the elements with these odd power sums, lowest term first;
    None if no such polynomial is short enough. Any field with ``mul`` and ``inverse`` will do."""
    t = len(sums)
    s = [0] * (2 * t + 1)
    for k, v in enumerate(sums):
        s[2 * k + 1] = v
    for k in range(1, t + 1):
        s[2 * k] = field.mul(s[k], s[k])
    s = s[1:]
    found, last, size, gap, last_gap = [1], [1], 0, 1, 1
    for n in range(2 * t):
        off = s[n]
        for k in range(1, min(size + 1, len(found))):
            off ^= field.mul(found[k], s[n - k])
        if not off:
            gap += 1
            continue
        scale = field.mul(off, field.inverse(last_gap))
        new = found + [0] * max(0, gap + len(last) - len(found))
        for k, c in enumerate(last):
            new[gap + k] ^= field.mul(scale, c)
        if 2 * size <= n:
            size, last, last_gap, gap = n + 1 - size, found, off, 1
        else:
            gap += 1
        found = new
    while found and not found[-1]:
        found.pop()
    return found if len(found) - 1 == size <= t else None


def decode(sums: list[int], width: int = 64) -> list[int] | None:
    """The elements whose odd power sums these are; None if there are more than the sketch holds."""
    field = Field(width)
    found = locator(sums, field)
    if found is None:
        return None
    roots = field.roots(found[::-1], random.Random(len(found) - 1))
    return roots if roots is not None and len(roots) == len(found) - 1 else None


class SmallField:
    """GF(2^q) of a bitmap's bins by tables of powers; ``decode`` tries every element."""

    #: Primitive polynomials by width.
    POLYNOMIALS = {6: 0x43, 7: 0x89, 8: 0x11D, 9: 0x211, 10: 0x409, 11: 0x805}

    def __init__(self, q: int):
        self.order = (1 << q) - 1
        powers, x = [], 1
        for _ in range(self.order):
            powers.append(x)
            x <<= 1
            if x >> q:
                x ^= self.POLYNOMIALS[q]
        self.power = powers * 2
        self.log = [0] * (self.order + 1)
        for k, x in enumerate(powers):
            self.log[x] = k
        self.power_np, self.log_np = np.array(self.power), np.array(self.log)

    def mul(self, a: int, b: int) -> int:
        return self.power[self.log[a] + self.log[b]] if a and b else 0

    def inverse(self, a: int) -> int:
        return self.power[self.order - self.log[a]]

    def sums(self, bins: np.ndarray, t: int) -> list[int]:
        """Odd power sums of the elements alpha^bin."""
        odd = 2 * np.arange(t)[:, None] + 1
        return np.bitwise_xor.reduce(self.power_np[bins[None, :].astype(np.int64) * odd % self.order], axis=1).tolist() if len(bins) else [0] * t

    def decode(self, sums: list[int]) -> np.ndarray | None:
        """The bins of a sketch; None where it holds more than it can tell."""
        found = locator(sums, self)
        if found is None:
            return None
        at = np.arange(self.order)
        value = np.full(self.order, found[0])
        for k, c in enumerate(found[1:], 1):
            if c:
                value ^= self.power_np[(self.log[c] - k * at) % self.order]
        bins = np.flatnonzero(value == 0)
        return bins if len(bins) == len(found) - 1 else None


@lru_cache(maxsize=None)
def small_field(q: int) -> SmallField:
    return SmallField(q)


def sketch_ledger(sizes: DataFrame) -> DataFrame:
    """Charges a sketch that an oracle sizes to exactly d, and the digests sent back for what only the sender has."""
    return ledger.lines(sizes, "syndrome_sketch", [
        (1, ledger.A, "sketch", F.col("d"), DIGEST_BYTES * F.col("d"), True),
        (1, ledger.B, "wanted_digests", F.col("a_only"), DIGEST_BYTES * F.col("a_only"), True), *payload_lines(sizes),
    ])


def syndrome_complete(elements: DataFrame, capacity: int, width: int = 64) -> DataFrame:
    """``syndrome_sketch``, repeated with twice the capacity for the scopes that fail until none does."""
    out, left = None, elements
    while True:
        got = settled(syndrome_sketch(left, capacity, width), "sketched")
        fine = got.where("decoded")
        out = fine if out is None else out.unionByName(fine)
        failed = got.where("not decoded").select("run_id", "shard")
        if not failed.limit(1).count():
            return out
        left, capacity = left.join(failed, ["run_id", "shard"], "left_semi"), 2 * capacity


def syndrome_sketch(elements: DataFrame, capacity: int, width: int = 64) -> DataFrame:
    """Really decodes, scope by scope: ``run_id, shard, digest, side, decoded``. Split a set into shards whose
    differences stay within ``capacity``: decoding takes the square of it. A scope that fails has one row."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        sides = {s: pdf.digest[pdf.side == s].to_numpy(np.int64) for s in (-1, 1)}
        sums = [a ^ b for a, b in zip(sketch(sides[-1], capacity, width), sketch(sides[1], capacity, width))]
        found = decode(sums, width)
        ids = np.array(found or [], np.uint64).view(np.int64)
        own = np.isin(ids, sides[1])  # the decoding side knows which ones it has
        n = max(1, len(ids))
        return pd.DataFrame({
            "run_id": [pdf.run_id.iloc[0]] * n, "shard": [pdf.shard.iloc[0]] * n, "digest": pd.array(ids.tolist() or [None], "Int64"),
            "side": pd.array(np.where(own, 1, -1).tolist() or [None], "Int32"), "decoded": [found is not None] * n,
        })

    return spread(elements, "run_id", "shard").groupBy("run_id", "shard").applyInPandas(run, "run_id string, shard int, digest long, side int, decoded boolean")
