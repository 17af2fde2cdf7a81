"""Token ids in compressed blocks: order-0 to order-2 predictions drive a range coder.

Every block starts from the same fresh model, so blocks are coded side by side: one numpy
step advances one id of every block ("lane").  An id is coded as a yes/no event, whether
it is what the order-2 or order-1 context saw last, with a probability mixed from both
contexts' records, and, if not, as a high and a low part under adaptive order-0
frequencies.  All model arithmetic is on integers, so decoding repeats encoding exactly.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np

# ---- fixed values of the file format
MAGIC, VERSION = b"WPID", 2
HEAD = struct.Struct("<4sBxHIqqIII")  # magic, version, fragments, ids, part, first id's place in the part, words, crc of ids, crc of what follows
FRAGMENT = struct.Struct("<qqIBI")  # document id, its number in the part, fragment number, 1 if its id is null, ids of it here
BLOCK_IDS = 2048
LOW_BITS, SLOTS1, SLOTS2 = 5, 4096, 8192
# ----
_U = np.uint64
_MASK48, _FULL, _LEAST = _U((1 << 48) - 1), _U(1 << 48), _U(1 << 32)
_ONE = 1 << 12


def _stretch_table() -> np.ndarray:
    p = (np.arange(4096) + 0.5) / 4096
    return np.rint(256 * np.log(p / (1 - p))).astype(np.int32)


def _squash_table() -> np.ndarray:
    z = np.arange(-2047, 2048) / 256
    return np.clip(np.rint(4096 / (1 + np.exp(-z))), 24, 4096 - 24).astype(np.int32)


STRETCH, SQUASH = _stretch_table(), _squash_table()


class _Model:
    """State of every lane; ``step`` is shared by coding and decoding through the ``coder`` callbacks."""

    def __init__(self, lanes: int, top: int):
        self.n, self.rows = lanes, np.arange(lanes)
        low = 1 << LOW_BITS
        self.size = ((top >> 2 * LOW_BITS) + 1, low, low)
        self.seen1 = np.zeros(lanes * SLOTS1, np.uint16)
        self.seen2 = np.zeros(lanes * SLOTS2, np.uint16)
        self.sure1 = np.zeros(lanes * SLOTS1, np.uint8)
        self.sure2 = np.zeros(lanes * SLOTS2, np.uint8)
        self.p1 = np.full(lanes * 16, 1 << 14, np.int32)
        self.p2 = np.full(lanes * 16, 1 << 14, np.int32)
        self.mix1 = np.full(lanes, 1 << 15, np.int32)
        self.mix2 = np.full(lanes, 1 << 15, np.int32)
        # cumulative order-0 counts of the three parts, one column more than there are values; low ids start out likelier
        first = np.r_[0, np.cumsum(np.maximum(1, 1024 // (np.arange(self.size[0]) + 3)))]
        even = 2 * np.arange(low + 1)
        self.counts = [np.tile(first.astype(np.uint16), (lanes, 1)), np.tile(even.astype(np.uint16), (lanes * self.size[0], 1)), np.tile(even.astype(np.uint16), (lanes * self.size[0] * low, 1))]
        self.more = [(np.arange(n + 1) > np.arange(n)[:, None]).astype(np.uint16) * np.uint16(24) for n in self.size]
        self.prev1 = np.zeros(lanes, np.int64)
        self.prev2 = np.zeros(lanes, np.int64)

    def begin(self, k: int):
        """Contexts and the mixed probability (of 4096) that the guess is right, for the first k lanes."""
        r = self.rows[:k]
        a, b = self.prev1[:k], self.prev2[:k]
        s1 = r * SLOTS1 + ((a * 40503) >> 4) % SLOTS1
        s2 = r * SLOTS2 + ((a * 40503 + b * 60493) >> 3) % SLOTS2
        c1, c2 = self.sure1[s1], self.sure2[s2]
        g1, g2 = self.seen1[s1], self.seen2[s2]
        guess = np.where(c2 > 0, g2, g1).astype(np.int64)
        same = (g1 == g2) & (c1 > 0) & (c2 > 0)
        x1 = r * 16 + c1 + 8 * same
        x2 = r * 16 + c2 + 8 * same
        t1, t2 = STRETCH[self.p1[x1] >> 4], STRETCH[self.p2[x2] >> 4]
        z = (t1 * (self.mix1[:k] >> 4) + t2 * (self.mix2[:k] >> 4)) >> 12
        p = SQUASH[np.clip(z, -2047, 2047) + 2047]
        return (s1, s2, c1, c2, g1, g2, x1, x2, t1, t2, p), guess, p

    def learn(self, k: int, ctx, hit: np.ndarray, ids: np.ndarray):
        s1, s2, c1, c2, g1, g2, x1, x2, t1, t2, p = ctx
        goal = hit * 65535
        self.p1[x1] += (goal - self.p1[x1]) >> 4
        self.p2[x2] += (goal - self.p2[x2]) >> 4
        err = hit * 4096 - p
        self.mix1[:k] = np.clip(self.mix1[:k] + ((t1 * err) >> 10), 0, 1 << 18)
        self.mix2[:k] = np.clip(self.mix2[:k] + ((t2 * err) >> 10), 0, 1 << 18)
        ok1, ok2 = g1 == ids, g2 == ids
        self.sure1[s1] = np.where(ok1, np.minimum(c1 + 1, 7), c1 >> 1)
        self.sure2[s2] = np.where(ok2, np.minimum(c2 + 1, 7), c2 >> 1)
        new1, new2 = ok1 | (c1 <= 1), ok2 | (c2 <= 1)
        self.seen1[s1] = np.where(new1, ids, g1)
        self.seen2[s2] = np.where(new2, ids, g2)
        self.sure1[s1] = np.maximum(self.sure1[s1], new1)
        self.sure2[s2] = np.maximum(self.sure2[s2], new2)
        self.prev2[:k] = self.prev1[:k]
        self.prev1[:k] = ids

    def parts(self, lanes: np.ndarray, ids: np.ndarray):
        """(level, rows of its table, values) of the three parts of ids."""
        a, b, c = ids >> 2 * LOW_BITS, (ids >> LOW_BITS) & (self.size[1] - 1), ids & (self.size[2] - 1)
        one = lanes * self.size[0] + a
        return (0, lanes, a), (1, one, b), (2, (one << LOW_BITS) + b, c)

    def grow(self, level: int, rows: np.ndarray, own: np.ndarray, values: np.ndarray):
        """Count the values; own are the rows as they were read."""
        new = own + self.more[level][values]
        if (new[:, -1] > 60000).any():
            big = np.flatnonzero(new[:, -1] > 60000)
            step = (np.diff(new[big].astype(np.int64), axis=1) + 1) >> 1
            new[big] = np.c_[np.zeros(len(big), np.int64), np.cumsum(step, 1)]
        self.counts[level][rows] = new


class _Encoder:
    def __init__(self, lanes: int, steps: int):
        self.low, self.range = np.zeros(lanes, _U), np.full(lanes, _FULL)
        self.out = np.zeros((lanes, 4 * steps + 6), np.int64)  # words may hold a carry until the end
        self.at = np.ones(lanes, np.int64)

    def put(self, lanes, start, size, total):
        step = self.range[lanes] // total
        low = self.low[lanes] + step * start
        width = step * size
        carry = low >= _FULL
        if carry.any():
            c = lanes[carry]
            self.out[c, self.at[c] - 1] += 1
            low &= _MASK48
        thin = width < _LEAST
        if thin.any():
            t = lanes[thin]
            self.out[t, self.at[t]] += (low[thin] >> _U(32)).astype(np.int64)
            self.at[t] += 1
            low[thin] = (low[thin] << _U(16)) & _MASK48
            width[thin] <<= _U(16)
        self.low[lanes], self.range[lanes] = low, width

    def end(self) -> list[bytes]:
        for shift in (32, 16, 0):
            self.out[np.arange(len(self.at)), self.at] += ((self.low >> _U(shift)) & _U(0xFFFF)).astype(np.int64)
            self.at += 1
        carry = np.zeros(len(self.at), np.int64)
        for i in range(int(self.at.max()) - 1, -1, -1):
            v = self.out[:, i] + carry
            self.out[:, i] = v & 0xFFFF
            carry = v >> 16
        words = self.out.astype("<u2")
        return [words[i, :n].tobytes() for i, n in enumerate(self.at)]


class _Decoder:
    def __init__(self, words: list[bytes]):
        n = max(map(len, words)) // 2 + 8
        self.words = np.zeros((len(words), n), _U)
        for i, w in enumerate(words):
            self.words[i, :len(w) // 2] = np.frombuffer(w, "<u2")
        self.range = np.full(len(words), _FULL)
        self.code = (self.words[:, 1] << _U(32)) | (self.words[:, 2] << _U(16)) | self.words[:, 3]
        self.at = np.full(len(words), 4, np.int64)

    def target(self, lanes, total):
        self.step = self.range[lanes] // total
        return np.minimum(self.code[lanes] // self.step, total - _U(1))

    def take(self, lanes, start, size):
        code = self.code[lanes] - self.step * start
        width = self.step * size
        thin = width < _LEAST
        if thin.any():
            t = lanes[thin]
            code[thin] = (code[thin] << _U(16)) | self.words[t, self.at[t]]
            self.at[t] += 1
            width[thin] <<= _U(16)
        self.code[lanes], self.range[lanes] = code, width


def encode_lanes(blocks: list[np.ndarray], top: int = 65535) -> list[bytes]:
    """A payload for each block of ids under ``top``."""
    if not blocks:
        return []
    order = sorted(range(len(blocks)), key=lambda i: -len(blocks[i]))
    size = np.array([len(blocks[i]) for i in order])
    steps = int(size[0]) if len(size) else 0
    ids = np.zeros((steps, len(blocks)), np.int64)
    for lane, i in enumerate(order):
        ids[:size[lane], lane] = blocks[i]
    model, coder = _Model(len(blocks), top), _Encoder(len(blocks), steps)
    live = np.searchsorted(-size, -np.arange(steps), side="left")  # lanes longer than t
    one = np.full(len(blocks), _U(_ONE))
    for t in range(steps):
        k = int(live[t])
        x = ids[t, :k]
        ctx, guess, p = model.begin(k)
        hit = (x == guess).astype(np.int32)
        pu = p.astype(_U)
        yes = hit > 0
        coder.put(model.rows[:k], np.where(yes, _U(0), pu), np.where(yes, pu, _U(_ONE) - pu), one[:k])
        miss = np.flatnonzero(~yes)
        if len(miss):
            pick = np.arange(len(miss))
            for level, rows, v in model.parts(miss, x[miss]):
                own = model.counts[level][rows]
                start = own[pick, v].astype(_U)
                coder.put(miss, start, own[pick, v + 1].astype(_U) - start, own[:, -1].astype(_U))
                model.grow(level, rows, own, v)
        model.learn(k, ctx, hit, x)
    out: list[bytes] = [b""] * len(blocks)
    for lane, words in enumerate(coder.end()):
        out[order[lane]] = words
    return out


def decode_lanes(payloads: list[bytes], sizes: list[int], top: int = 65535) -> list[np.ndarray]:
    """The ids of each payload."""
    if not payloads:
        return []
    order = sorted(range(len(payloads)), key=lambda i: -sizes[i])
    size = np.array([sizes[i] for i in order])
    steps = int(size[0])
    ids = np.zeros((steps, len(payloads)), np.int64)
    model, coder = _Model(len(payloads), top), _Decoder([payloads[i] for i in order])
    live = np.searchsorted(-size, -np.arange(steps), side="left")
    for t in range(steps):
        k = int(live[t])
        lanes = model.rows[:k]
        ctx, guess, p = model.begin(k)
        pu = p.astype(_U)
        yes = coder.target(lanes, _U(_ONE)) < pu
        coder.take(lanes, np.where(yes, _U(0), pu), np.where(yes, pu, _U(_ONE) - pu))
        x = guess.copy()
        miss = np.flatnonzero(~yes)
        if len(miss):
            pick, rows, whole = np.arange(len(miss)), miss, np.zeros(len(miss), np.int64)
            for level in range(3):
                own = model.counts[level][rows]
                at = coder.target(miss, own[:, -1].astype(_U)).astype(np.uint16)
                v = (own[:, 1:] <= at[:, None]).sum(1)
                start = own[pick, v].astype(_U)
                coder.take(miss, start, own[pick, v + 1].astype(_U) - start)
                model.grow(level, rows, own, v)
                whole = (whole << (LOW_BITS if level else 0)) | v
                rows = rows * model.size[level] + v
            x[miss] = whole
        ids[t, :k] = x
        model.learn(k, ctx, yes.astype(np.int32), x)
    out: list[np.ndarray] = [np.zeros(0, np.uint32)] * len(payloads)
    for lane, i in enumerate(order):
        out[i] = ids[:size[lane], lane].astype(np.uint32)
    return out


def block_bytes(part: int, place: int, fragments: list[tuple], ids: np.ndarray, payload: bytes) -> bytes:
    """A self-describing block: header with both checksums, fragment list, coded words."""
    body = b"".join(FRAGMENT.pack(0 if d is None else d, number, frag, d is None, n) for d, number, frag, n in fragments) + payload
    return HEAD.pack(MAGIC, VERSION, len(fragments), len(ids), part, place, len(payload), zlib.crc32(ids.astype("<u4").tobytes()), zlib.crc32(body)) + body


def read_block(blob: bytes) -> tuple:
    """(part, place, fragments, number of ids, crc of ids, payload); raises on a damaged block."""
    magic, version, frags, n, part, place, size, crc, body_crc = HEAD.unpack_from(blob)
    body = blob[HEAD.size:]
    if magic != MAGIC or version != VERSION or zlib.crc32(body) != body_crc:
        raise ValueError("damaged block")
    fragments = [FRAGMENT.unpack_from(body, i * FRAGMENT.size) for i in range(frags)]
    payload = body[frags * FRAGMENT.size:]
    if len(payload) != size:
        raise ValueError("damaged block")
    return part, place, [(None if null else d, number, frag, m) for d, number, frag, null, m in fragments], n, crc, payload


# ---------------------------------------------------------------- checksums of joined parts

_POLY = 0xEDB88320


def _times(a: int, b: int) -> int:
    """Product of two polynomials in the checksum's field, bits reversed."""
    out, m = 0, 1 << 31
    while m:
        if a & m:
            out ^= b
        b = (b >> 1) ^ (_POLY if b & 1 else 0)
        m >>= 1
    return out


def crc_joined(first: int, second: int, second_bytes: int) -> int:
    """crc32 of two byte strings one after the other, from their checksums and the second's length."""
    power, square, n = 1 << 31, 1 << 30, 8 * second_bytes  # x^0 and x^1
    while n:
        if n & 1:
            power = _times(square, power)
        square = _times(square, square)
        n >>= 1
    return _times(power, first) ^ second
