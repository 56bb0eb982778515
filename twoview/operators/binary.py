"""Binary codes to compare with: signs of random rotations or projections, and a learned rotation."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from twoview.operators.linear import fit_pca, random_rotation
from twoview.operators.model import LinearMap, ModelSpec, pack_words
from twoview.operators.vectors import collect_matrix, map_vectors


@dataclass
class BinaryModel:
    """Bit t of a vector is set where component t of its image is not negative."""

    image: LinearMap
    bits: int

    @property
    def n_words(self) -> int:
        return -(-self.bits // 64)

    def words(self, x: np.ndarray) -> np.ndarray:
        signs = (self.image.apply(x) >= 0).astype(np.int64)
        return pack_words(signs, ModelSpec(self.bits, self.bits, 1))


def fit_sign_lsh(dims: int, bits: int, seed: int = 0, orthogonal: bool = True, mean: np.ndarray | None = None) -> BinaryModel:
    """Random directions; orthogonal ones in blocks of as many as there are dimensions."""
    rng = np.random.default_rng(seed)
    if orthogonal:
        blocks = [random_rotation(dims, seed * 1000 + i).matrix for i in range(-(-bits // dims))]
        m = np.concatenate(blocks, 1)[:, :bits]
    else:
        m = rng.normal(size=(dims, bits))
    return BinaryModel(LinearMap(m, np.zeros(dims) if mean is None else mean), bits)


def fit_itq(train: DataFrame, dims: int, bits: int, iters: int = 50, seed: int = 0, max_rows: int = 100_000) -> BinaryModel:
    """Principal components, then the rotation that brings them nearest to their signs, by turns."""
    bits_pca = min(bits, dims)
    pca = fit_pca(train, dims, bits_pca)
    _, x = collect_matrix(train, max_rows)
    v = pca.apply(x)
    r = random_rotation(bits_pca, seed).matrix
    for _ in range(iters):
        b = np.where(v @ r >= 0, 1.0, -1.0)
        u, _, wt = np.linalg.svd(v.T @ b)
        r = u @ wt
    m = pca.matrix @ r
    if bits > bits_pca:  # more bits than dimensions: further rotations of the same components
        m = np.concatenate([m, *[pca.matrix @ random_rotation(bits_pca, seed + 1 + i).matrix for i in range(-(-bits // bits_pca) - 1)]], 1)[:, :bits]
    return BinaryModel(LinearMap(m, pca.mean), bits)


def encode_bits(df: DataFrame, model: BinaryModel, prefix: str = "w", id_name: str = "vec_id", keep: list[str] | None = None) -> DataFrame:
    """Bits as words prefix0, prefix1, ..."""
    sent = df.sparkSession.sparkContext.broadcast(model)

    def one(x: np.ndarray) -> dict[str, np.ndarray]:
        w = sent.value.words(x)
        return {f"{prefix}{i}": w[:, i] for i in range(model.n_words)}

    schema = ", ".join(f"{prefix}{i} bigint" for i in range(model.n_words))
    return map_vectors(df, one, schema, keep).withColumnRenamed("vec_id", id_name)


def bit_spec(model: BinaryModel) -> ModelSpec:
    """The shape of a binary code as a code of one-bit numbers."""
    return ModelSpec(model.bits, model.bits, 1)
