"""l0 samplers over edge ids: the one-level sampler, the nested one it improves on, and their kernels.

A sampler has ``columns`` columns of ``levels`` buckets and one checksum over its whole vector. Under
the column's hash an edge id belongs to the level of its trailing zeros: the one-level sampler
writes that bucket alone, the nested one all buckets up to it. A bucket is (xor of ids, xor of their
checksums). A bucket holds one id when its checksum is that of its id. Whether a vector is empty is
told by the whole checksum only: ids of a dense graph cancel to 0 without any being empty.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from typing import Protocol

import numpy as np

from edgesketch.functions.hashing import mix64

EDGE, EMPTY, FAILED = 0, 1, 2
UPDATE_BYTES = 9  # two 4-byte ids and a sign
STATUS = {EDGE: "edge", EMPTY: "empty", FAILED: "failed"}
_CHECK_SEED = 0x5EED


@dataclass(frozen=True)
class SketchParams:
    """What two sketches must share to be added."""

    v_count: int
    variant: str = "one_level"
    copies: int = 1
    samplers: int | None = None
    columns: int = 2
    levels: int | None = None
    seed: int = 42
    hash_family: str = "mix64"
    #: The number of the first copy: copy i of a larger sketch has the hashes of a sketch of one copy that starts at i.
    first_copy: int = 0

    def __post_init__(self):
        if self.variant not in ("one_level", "nested") or self.hash_family not in ("mix64", "xxhash64", "pair31"):
            raise ValueError(f"unknown variant or hash family: {self.variant}, {self.hash_family}")
        if self.copies < 1 or self.columns < 1:
            raise ValueError("a sketch has at least one copy and one column")
        v = max(2, self.v_count)
        if self.samplers is None:
            object.__setattr__(self, "samplers", max(1, math.ceil(math.log(v, 1.5))))
        if self.levels is None:
            object.__setattr__(self, "levels", min(62, math.ceil(2 * math.log2(v))))

    @classmethod
    def for_edges(cls, v_count: int, most_edges: int, **rest) -> SketchParams:
        """Levels for a known bound of edges."""
        return cls(v_count, levels=min(62, math.ceil(math.log2(max(2, most_edges))) + 2), **rest)

    @property
    def words(self) -> int:
        """64-bit words of one sampler of one vertex."""
        return 2 * self.columns * self.levels + 1

    @property
    def body_bytes(self) -> int:
        return 8 * self.words

    @property
    def vertex_bytes(self) -> int:
        return self.copies * self.samplers * self.body_bytes

    def capacity(self, alpha: float = 1.0) -> int:
        """Updates of a full vertex batch: alpha times the vertex sketch.

        An update is in the batches of both its ends, so each counts half of its bytes; with more of
        them, deltas of batches that are just full enough would pass the communication bound.
        """
        return math.ceil(alpha * self.vertex_bytes / (UPDATE_BYTES / 2))

    def key(self) -> tuple:
        return (self.v_count, self.variant, self.copies, self.samplers, self.columns, self.levels, self.seed, self.hash_family, self.first_copy)

    def with_(self, **changes) -> SketchParams:
        return replace(self, **changes)

    def column_seed(self, copy: int, sampler: int, col: int) -> int:
        return ((self.seed * 1_000_003 + self.first_copy + copy) * 1_000_003 + sampler) * 64 + col + 1

    def copy(self, i: int) -> SketchParams:
        """The parameters of copy i alone."""
        return self.with_(copies=1, first_copy=self.first_copy + i)


class Kernel(Protocol):
    """Any vertex-linear sketch fits the batching and merging frame by these."""

    def toggle(self, body: np.ndarray, group: np.ndarray, eids: np.ndarray) -> None: ...

    def decode(self, body: np.ndarray) -> tuple[np.ndarray, np.ndarray]: ...


def checksum(eids: np.ndarray, params: SketchParams) -> np.ndarray:
    return mix64(eids, params.seed ^ _CHECK_SEED)


#: Ids that a kernel works on at once: small enough to stay in the processor's cache.
BLOCK_IDS = 1 << 14


def _runs_xor(x: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The xor of each run of x, from the last places of the runs."""
    upto = np.bitwise_xor.accumulate(x)[ends]
    out = upto.copy()
    out[1:] ^= upto[:-1]
    return out


class SamplerKernel:
    """The samplers of all copies of a vertex sketch; bodies are rows of uint64 words."""

    def __init__(self, params: SketchParams):
        self.params = params
        self.width = params.copies * params.samplers * params.words
        self.examined = self.written = 0

    def zeros(self, n: int) -> np.ndarray:
        return np.zeros((n, self.width), np.uint64)

    def toggle(self, body: np.ndarray, group: np.ndarray, eids: np.ndarray) -> None:
        """Xors every id into the buckets of its row ``group``, block by block of ids in the order of their rows."""
        if not len(eids):
            return
        if (group[1:] < group[:-1]).any():
            order = np.argsort(group, kind="stable")
            group, eids = group[order], eids[order]
        p = self.params
        check = checksum(eids, p)
        new = np.ones(len(group), bool)
        np.not_equal(group[1:], group[:-1], out=new[1:])
        heads = np.flatnonzero(new)
        most = 65535 // (p.levels + 1)  # rows of a block, so that (row, level) sorts as 16 bits
        at = k = 0
        while at < len(eids):
            stop = min(at + BLOCK_IDS, int(heads[k + most]) if k + most < len(heads) else len(eids))
            self._block(body, group[at:stop], eids[at:stop], check[at:stop])
            at = stop
            k = int(np.searchsorted(heads, at, side="right")) - 1

    def _block(self, body: np.ndarray, group: np.ndarray, eids: np.ndarray, check: np.ndarray) -> None:
        p, n, flat = self.params, len(eids), body.reshape(-1)
        new = np.empty(n, bool)
        new[0] = False
        np.not_equal(group[1:], group[:-1], out=new[1:])
        heads = np.flatnonzero(new)
        rows = group[np.concatenate([[0], heads])]
        ends = np.append(heads - 1, n - 1)
        body.reshape(len(body), -1, p.words)[rows, :, -1] ^= _runs_xor(check, ends)[:, None]
        row = np.cumsum(new, dtype=np.uint16) * np.uint16(p.levels)
        cell = (rows.astype(np.int64)[:, None] * self.width + 2 * np.arange(p.levels)).reshape(-1)
        top, spare, low = np.uint8(p.levels), np.empty(n, np.uint64), np.empty(n, np.uint64)
        for copy in range(p.copies):
            for s in range(p.samplers):
                for c in range(p.columns):
                    first = (copy * p.samplers + s) * p.words + 2 * c * p.levels
                    h = mix64(eids, p.column_seed(copy, s, c), low, spare)
                    # the bits up to the lowest that is set: a level, and one
                    np.subtract(h, np.uint64(1), out=spare)
                    level = np.minimum(np.bitwise_count(np.bitwise_xor(h, spare, out=spare)), top)
                    if p.variant == "one_level":
                        self._once(flat, cell, first, row + level - np.uint16(1), eids, check)
                    else:
                        self._nested(flat, cell, first, row, level, eids, check)

    def _once(self, flat, cell, first, key, eids, check) -> None:
        """One bucket of each id: runs of equal (row, level) are xored and written once."""
        order = np.argsort(key, kind="stable")
        key = key[order]
        ends = np.append(np.flatnonzero(key[1:] != key[:-1]), len(key) - 1)
        at = cell[key[ends]] + first
        flat[at] ^= _runs_xor(eids[order], ends)
        flat[at + 1] ^= _runs_xor(check[order], ends)
        self.examined += len(eids)
        self.written += len(eids)

    def _nested(self, flat, cell, first, row, level, eids, check) -> None:
        """All buckets up to the level of each id, level by level."""
        for k in range(self.params.levels):
            some = np.flatnonzero(level > k)
            self.examined += len(eids)
            self.written += len(some)
            if len(some):
                key = row[some]
                ends = np.append(np.flatnonzero(key[1:] != key[:-1]), len(key) - 1)
                at = cell[key[ends] + np.uint16(k)] + first
                flat[at] ^= _runs_xor(eids[some], ends)
                flat[at + 1] ^= _runs_xor(check[some], ends)

    def sketch(self, group: np.ndarray, eids: np.ndarray, n: int) -> np.ndarray:
        body = self.zeros(n)
        self.toggle(body, group, eids)
        return body

    def decode(self, body: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(status, id) of one sampler for each row of ``words`` words, sparse levels first."""
        p = self.params
        n = len(body)
        pairs = body[:, :-1].reshape(n, p.columns, p.levels, 2)[:, :, ::-1].reshape(n, -1, 2)
        ids, checks = pairs[:, :, 0], pairs[:, :, 1]
        lo, hi = ids >> np.uint64(32), ids & np.uint64(0xFFFFFFFF)
        good = (ids != 0) & (lo < hi) & (hi < np.uint64(p.v_count)) & (checksum(ids, p) == checks)
        status = np.where(body[:, -1] == 0, EMPTY, np.where(good.any(axis=1), EDGE, FAILED))
        pick = good.argmax(axis=1)
        return status, np.where(status == EDGE, ids[np.arange(n), pick], np.uint64(0))


def nested_from_one_level(body: np.ndarray, params: SketchParams) -> np.ndarray:
    """The nested buckets are the suffix xor of the one-level ones, for equal hashes."""
    out = body.copy()
    view = out.reshape(-1, params.words)[:, :-1].reshape(-1, params.columns, params.levels, 2)
    view[:] = np.bitwise_xor.accumulate(view[:, :, ::-1], axis=2)[:, :, ::-1]
    return out
