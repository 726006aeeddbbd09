"""Arrow helpers of the operators."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def numpy_of(lists: pa.Array, width: int) -> np.ndarray:
    """A list column without nulls, all of one width, as a matrix."""
    return lists.flatten().to_numpy(zero_copy_only=False).reshape(-1, width)
