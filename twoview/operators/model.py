"""What a trained code is: sizes, codebook, numbering, and the maps before it."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass(frozen=True)
class ModelSpec:
    """D dimensions in M slices, each quantized to 2**b centroids."""

    D: int
    M: int
    b: int = 8

    def __post_init__(self) -> None:
        if self.D % self.M:
            raise ValueError(f"{self.D} dimensions can't be cut into {self.M} equal slices")
        if not 1 <= self.b <= 16:
            raise ValueError("b must be from 1 to 16")

    @property
    def K(self) -> int:
        return 1 << self.b

    @property
    def ds(self) -> int:
        return self.D // self.M

    @property
    def per_word(self) -> int:
        return 64 // self.b

    @property
    def n_words(self) -> int:
        return -(-self.M // self.per_word)

    @property
    def bits(self) -> int:
        return self.M * self.b

    @property
    def code_bytes(self) -> int:
        return -(-self.bits // 8)


@dataclass
class LinearMap:
    """x -> (x - mean) @ matrix."""

    matrix: np.ndarray
    mean: np.ndarray

    def apply(self, x: np.ndarray) -> np.ndarray:
        return (x - self.mean) @ self.matrix

    def then(self, other: LinearMap) -> LinearMap:
        return LinearMap(self.matrix @ other.matrix, self.mean + np.linalg.lstsq(self.matrix.T, other.mean, rcond=None)[0])


@dataclass
class CodeModel:
    """A quantizer whose centroids already stand in the order of their numbers."""

    spec: ModelSpec
    codebook: np.ndarray  # M, K, ds
    tau: int | None = None
    before: LinearMap | None = None
    construction: str = "plain"
    info: dict = field(default_factory=dict)

    def slices(self, x: np.ndarray) -> np.ndarray:
        """Sub-vectors: M, rows, ds."""
        x = self.before.apply(x) if self.before is not None else x
        return np.ascontiguousarray(x.reshape(len(x), self.spec.M, self.spec.ds).transpose(1, 0, 2))

    def tables(self, x: np.ndarray) -> np.ndarray:
        """Squared distances of each row's slices to all centroids: rows, M * K."""
        s = self.slices(x)
        out = np.empty((len(x), self.spec.M, self.spec.K))
        for m in range(self.spec.M):
            d = s[m][:, None, :] - self.codebook[m][None]
            out[:, m] = np.einsum("nkd,nkd->nk", d, d)
        return out.reshape(len(x), -1)

    def encode(self, x: np.ndarray, block: int = 2048) -> np.ndarray:
        """Numbers of the nearest centroids, the smaller one of equals: rows, M."""
        parts = [self.tables(x[a : a + block]).reshape(-1, self.spec.M, self.spec.K).argmin(2) for a in range(0, len(x), block)]
        return np.concatenate(parts) if parts else np.zeros((0, self.spec.M), np.int64)

    def decode(self, codes: np.ndarray) -> np.ndarray:
        return np.concatenate([self.codebook[m][codes[:, m]] for m in range(self.spec.M)], axis=1)

    def relabelled(self, pi: np.ndarray, construction: str) -> CodeModel:
        """The same quantizer with centroid i of slice m numbered pi[m, i]; estimates by look-up don't change."""
        book = np.empty_like(self.codebook)
        for m in range(self.spec.M):
            if sorted(pi[m]) != list(range(self.spec.K)):
                raise ValueError("a numbering must be a bijection")
            book[m][pi[m]] = self.codebook[m]
        return CodeModel(self.spec, book, None, self.before, construction, dict(self.info))


def pack_words(codes: np.ndarray, spec: ModelSpec) -> np.ndarray:
    """Numbers to 64-bit words: rows, n_words, as signed integers."""
    out = np.zeros((len(codes), spec.n_words), np.uint64)
    for m in range(spec.M):
        out[:, m // spec.per_word] |= codes[:, m].astype(np.uint64) << np.uint64(spec.b * (m % spec.per_word))
    return out.view(np.int64)


def unpack_words(words: np.ndarray, spec: ModelSpec) -> np.ndarray:
    """Words back to numbers."""
    w = words.view(np.uint64)
    shifts = [np.uint64(spec.b * (m % spec.per_word)) for m in range(spec.M)]
    return np.stack([(w[:, m // spec.per_word] >> shifts[m]) & np.uint64(spec.K - 1) for m in range(spec.M)], 1).astype(np.int64)
