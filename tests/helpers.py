import numpy as np

from blocksketch.operators.matrix import CoordMatrix

DATA = "/root/testdata/sf0.001"


def coords(spark, x: np.ndarray) -> CoordMatrix:
    rows = [(int(i), int(c), int(x[i, c])) for i, c in zip(*np.nonzero(x), strict=True)]
    return CoordMatrix(spark.createDataFrame(rows, "i long, c long, v long"), *x.shape)


def array(m, row="i", col="c", v="v", shape=None) -> np.ndarray:
    df, shape = (m.df, (m.rows, m.cols)) if isinstance(m, CoordMatrix) else (m, shape)
    out = np.zeros(shape)
    for i, c, x in df.select(row, col, v).collect():
        out[i, c] = x
    return out


def tiny(seed=0):
    """4 x 6 and 6 x 3 with an empty row, an empty column and negative entries."""
    rng = np.random.default_rng(seed)
    a, b = rng.integers(-4, 5, (4, 6)), rng.integers(-4, 5, (6, 3))
    a[2] = 0
    a[:, 4] = 0
    return a, b
