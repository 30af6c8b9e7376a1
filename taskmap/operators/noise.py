"""The deterministic noise of edges over arrays; the Column form is in taskmap.operators.matching."""

import numpy as np

#: The modulus and factors of the deterministic noise.
NOISE_MODULUS = 1_000_003
NOISE_FACTORS = (73_856_093, 19_349_663, 83_492_791)


def edge_noise_array(a: np.ndarray, b: np.ndarray, seed: int = 0) -> np.ndarray:
    p, (x, y, z) = NOISE_MODULUS, NOISE_FACTORS
    low, high = np.minimum(a, b).astype(np.int64), np.maximum(a, b).astype(np.int64)
    return ((low % p) * x + (high % p) * y + (seed % p) * z) % p
