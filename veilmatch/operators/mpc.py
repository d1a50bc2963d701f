"""Two-party computation on additive shares mod 2**64 with a third, dealing party, as numpy kernels.

A shared value is a pair of uint64 arrays, one of each proxy. The proxies are 0 and 1, the dealer is 2. All randomness
comes from a keyed extendable-output function, named by session, block and use, so a repeated
task repeats its messages and no mask is ever used for other data. Every opening and everything
that cannot be derived from a key is written to a ledger: bytes by step, sender, receiver and phase, and rounds.

The kernels follow published techniques: multiplication, dot and matrix products by dealt triples; signs and zero tests by
opening a masked value and handing the dealer its bitwise comparison with the mask, blinded by factors, a rotation
and a flip that only the proxies know. Both take three rounds, whatever the word length.
"""

from __future__ import annotations

import hashlib
from collections import defaultdict

import numpy as np

U = np.uint64
Shared = tuple[np.ndarray, np.ndarray]
WORD = 8  # bytes of a ring element
PLACES, FIELD = 64, 67  # bits of a ring element, and a prime above PLACES + 1
SLICE = 4096  # elements whose bits are handled at once


class Stream:
    """Random numbers of one name under a key."""

    def __init__(self, key: str, name: str):
        self.seed = hashlib.sha256(f"{key}|{name}".encode()).digest()
        self.calls = 0

    def bytes(self, n: int) -> bytes:
        self.calls += 1
        return hashlib.shake_128(self.seed + self.calls.to_bytes(8, "little")).digest(n)

    def words(self, shape) -> np.ndarray:
        n = int(np.prod(shape, dtype=np.int64))
        return np.frombuffer(self.bytes(WORD * n), U).reshape(shape)

    def below(self, shape, most: int) -> np.ndarray:
        """Uniform numbers below ``most``, at most 256: bytes that would favour some are left out."""
        need, top = int(np.prod(shape, dtype=np.int64)), 256 // most * most
        got = np.zeros(0, np.uint8)
        while len(got) < need:
            raw = np.frombuffer(self.bytes((need - len(got)) * 256 // top + 64), np.uint8)
            got = np.concatenate((got, raw[raw < top]))
        return (got[:need] % most).reshape(shape)


class Session:
    """One run of the protocol on one block; ``offline`` charges the dealer's messages to a phase before the inputs."""

    def __init__(self, key: str, block: str = "", offline: bool = False):
        self.key, self.block = key, block
        self.dealer, self.common, self.owners = (Stream(key, f"{who}|{block}") for who in ("dealer", "common", "owners"))
        self.bytes_: dict[tuple[str, int, int, str], int] = defaultdict(int)
        self.rounds: dict[str, int] = defaultdict(int)
        self.step = "input"
        self.phase = "offline" if offline else "online"

    def send(self, src: int, dst: int, n: int, phase: str = "online") -> None:
        if n:
            self.bytes_[self.step, src, dst, phase] += n

    def opened(self, words: int) -> None:
        """Both proxies send ``words`` ring elements to each other, in one round."""
        self.send(0, 1, WORD * words)
        self.send(1, 0, WORD * words)
        self.rounds[self.step] += 1

    def dealt(self, n: int) -> None:
        """Bytes that the dealer sends because they do not follow from a key."""
        self.send(2, 1, n, self.phase)

    def split(self, value: np.ndarray, name: str | None = None) -> Shared:
        """Shares of an owner's value; under a name the same shares in every block."""
        r = (Stream(self.key, f"split|{name}") if name else self.owners).words(value.shape)
        return r, value.astype(U) - r

    def split_bits(self, value: np.ndarray) -> Shared:
        r = self.owners.words(value.shape)
        return r, value ^ r

    def mask(self, shape, name: str | None = None) -> tuple[np.ndarray, Shared]:
        """A random value that the dealer knows, and its shares."""
        source = Stream(self.key, f"mask|{name}") if name else self.dealer
        a0, a1 = source.words(shape), source.words(shape)
        return a0 + a1, (a0, a1)

    def _product(self, value: np.ndarray) -> Shared:
        """Dealt shares of a product of masks: the second needs a message."""
        c0 = self.dealer.words(value.shape)
        self.dealt(WORD * value.size)
        return c0, value - c0

    def multiply(self, a: Shared, b: Shared) -> Shared:
        shape = np.broadcast_shapes(a[0].shape, b[0].shape)
        a, b = (tuple(np.broadcast_to(p, shape) for p in v) for v in (a, b))
        (alpha, al), (beta, be) = self.mask(shape), self.mask(shape)
        c = self._product(alpha * beta)
        d, e = (a[0] - al[0]) + (a[1] - al[1]), (b[0] - be[0]) + (b[1] - be[1])
        self.opened(2 * d.size)
        return d * e + d * be[0] + e * al[0] + c[0], d * be[1] + e * al[1] + c[1]

    def multiply_fixed(self, a: Shared, b: Shared) -> Shared:
        """One vector with every row of b; the masked vector is opened once for all rows."""
        (alpha, al), (beta, be) = self.mask(a[0].shape), self.mask(b[0].shape)
        c = self._product(alpha * beta)
        d, e = (a[0] - al[0]) + (a[1] - al[1]), (b[0] - be[0]) + (b[1] - be[1])
        self.opened(d.size + e.size)
        return d * e + d * be[0] + e * al[0] + c[0], d * be[1] + e * al[1] + c[1]

    def gram(self, x: Shared, y: Shared, names: tuple[str | None, str | None] = (None, None), first: tuple[bool, bool] = (True, True)) -> Shared:
        """All inner products of rows of x with rows of y.

        Each masked row is opened once: a side with a name keeps its mask in all blocks, and only the first block that it
        appears in sends it.
        """
        (a, al), (b, be) = self.mask(x[0].shape, names[0]), self.mask(y[0].shape, names[1])
        c = self._product(a @ b.T)
        e, f = (x[0] - al[0]) + (x[1] - al[1]), (y[0] - be[0]) + (y[1] - be[1])
        self.opened(e.size * first[0] + f.size * first[1])
        return e @ f.T + e @ be[0].T + al[0] @ f.T + c[0], e @ be[1].T + al[1] @ f.T + c[1]

    def both(self, a: Shared, b: Shared) -> Shared:
        """AND of shared bit words."""
        (alpha, al), (beta, be) = ((v[0] ^ v[1], v) for v in ((self.dealer.words(a[0].shape), self.dealer.words(a[0].shape)) for _ in range(2)))
        c0 = self.dealer.words(a[0].shape)
        c = c0, (alpha & beta) ^ c0
        self.dealt(WORD * c0.size)
        d, e = a[0] ^ al[0] ^ a[1] ^ al[1], b[0] ^ be[0] ^ b[1] ^ be[1]
        self.opened(2 * d.size)
        return (d & e) ^ (d & be[0]) ^ (e & al[0]) ^ c[0], (d & be[1]) ^ (e & al[1]) ^ c[1]

    def to_ring(self, bits: Shared) -> Shared:
        """Shared bits (arrays of 0 and 1) as ring shares, by dealt bits that are shared both ways; opened bits travel packed."""
        b = self.dealer.below(bits[0].shape, 2).astype(U)
        x0, r0 = self.dealer.below(b.shape, 2).astype(U), self.dealer.words(b.shape)
        self.dealt(WORD * b.size + -(-b.size // 8))
        v = bits[0] ^ x0 ^ bits[1] ^ (b ^ x0)
        n = -(-b.size // 8)
        self.send(0, 1, n)
        self.send(1, 0, n)
        self.rounds[self.step] += 1
        flip = v == 1
        return np.where(flip, U(1) - r0, r0), np.where(flip, U(0) - (b - r0), b - r0)

    def _masked(self, u: Shared) -> tuple[np.ndarray, np.ndarray]:
        """The opened u + rho, and rho, which only the dealer knows whole."""
        rho, r = self.mask(u[0].shape)
        t = (u[0] + r[0]) + (u[1] + r[1])
        self.opened(t.size)
        return t, rho

    def _told(self, public: np.ndarray, secret: np.ndarray, known: np.ndarray, zero: bool) -> Shared:
        """Ring shares of [secret > public], or with ``zero`` of [secret = public], each xor ``known``, which the dealer has.

        A vector of the first place where the two differ has one zero or none. The proxies form it on shares mod FIELD from the dealt
        bits of ``secret``, for the question or for its contrary by a common coin, multiply its places by common
        factors, rotate it, and send it to the dealer, who learns nothing from finding a zero.
        """
        shape, n = public.shape, public.size
        coin = self.common.below((n, 1), 2).astype(np.int16)
        other = public.ravel() + (coin[:, 0].astype(U) if not zero else U(0))
        self.dealt(PLACES * n)
        for party in (0, 1):
            self.send(party, 2, PLACES * n)
        found = np.empty(n, U)
        for lo in range(0, n, SLICE):
            rows = slice(lo, lo + SLICE)
            found[rows] = self._zeros(other[rows], secret.ravel()[rows], coin[rows], zero)
        self.rounds[self.step] += 1
        # With ``zero``, a zero says that the two differ unless the coin turns it; both turn back what they know.
        told = found ^ known.ravel().astype(U)
        r0 = self.dealer.words(n)
        self.send(2, 1, WORD * n)
        self.rounds[self.step] += 1
        flip = (coin[:, 0] == (0 if zero else 1))
        shares = np.where(flip, U(1) - r0, r0), np.where(flip, U(0) - (told - r0), told - r0)
        return shares[0].reshape(shape), shares[1].reshape(shape)

    def _zeros(self, public: np.ndarray, secret: np.ndarray, coin: np.ndarray, zero: bool) -> np.ndarray:
        """Whether the dealer finds a zero in the vector of each element."""
        bit = lambda v: np.unpackbits(v.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1).astype(np.int16)
        t, s = bit(public), bit(secret)
        s0 = self.dealer.below(s.shape, FIELD).astype(np.int16)
        factor = self.common.below(s.shape, FIELD - 1).astype(np.int16) + np.int16(1)
        order = (np.arange(PLACES) + self.common.below((len(t), 1), PLACES)) % PLACES
        turned = 1 - 2 * t
        total = np.zeros(s.shape, np.int16)
        for one, own in ((np.int16(1), s0), (np.int16(0), reduced(s - s0))):  # public terms are added by one proxy
            differs = own * turned + one * t
            above = np.cumsum(differs, axis=1, dtype=np.int16) - differs
            if zero:  # a zero at the first difference, or with the coin in one place if there is no difference
                c = np.where(coin == 1, one, one - differs + above)
                c[:, 0] = np.where(coin[:, 0] == 1, above[:, -1] + differs[:, -1], c[:, 0])
            else:  # a zero where the secret has the higher bit, or with the coin the public value has it
                c = one + (1 - 2 * coin) * (one * t - own) + above
            total += np.take_along_axis(reduced(reduced(c) * factor), order, 1)
        return (reduced(total) == 0).any(axis=1)

    def negative(self, u: Shared) -> Shared:
        """1 where the signed value is below zero: top bit of t less that of rho, less the borrow from below."""
        t, rho = self._masked(u)
        low = U((1 << 63) - 1)
        bit = self._told(t & low, rho & low, rho >> U(63), False)
        flip = (t >> U(63)) == 1
        return np.where(flip, U(1) - bit[0], bit[0]), np.where(flip, U(0) - bit[1], bit[1])

    def greater(self, a: Shared, b: Shared) -> Shared:
        return self.negative(sub(b, a))

    def equal(self, a: Shared, b: Shared) -> Shared:
        t, rho = self._masked(sub(a, b))
        return self._told(t, rho, np.zeros(t.shape, U), True)

    def select(self, bit: Shared, a: Shared, b: Shared) -> Shared:
        """a where the bit is 1, else b."""
        return add(b, self.multiply(bit, sub(a, b)))

    def ledger(self) -> list[tuple[str, int, int, str, int, int]]:
        """(step, src, dst, phase, n_bytes, n_rounds)."""
        return [(step, src, dst, phase, n, self.rounds[step]) for (step, src, dst, phase), n in sorted(self.bytes_.items())]


def reduced(x: np.ndarray) -> np.ndarray:
    """x mod FIELD; by a division, which numpy has vectorised."""
    return x - np.floor_divide(x, np.int16(FIELD)) * np.int16(FIELD)


def reveal(a: Shared) -> np.ndarray:
    return a[0] + a[1]


def add(a: Shared, b: Shared) -> Shared:
    return a[0] + b[0], a[1] + b[1]


def sub(a: Shared, b: Shared) -> Shared:
    return a[0] - b[0], a[1] - b[1]


def scale(a: Shared, c: int) -> Shared:
    return a[0] * U(c), a[1] * U(c)


def stacked(*values: Shared) -> Shared:
    """Shared arrays of one shape as one, so that their messages go together."""
    return np.stack([v[0] for v in values]), np.stack([v[1] for v in values])


def each(a: Shared) -> list[Shared]:
    return [(a[0][i], a[1][i]) for i in range(len(a[0]))]
