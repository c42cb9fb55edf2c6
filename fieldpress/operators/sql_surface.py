"""SQL functions of a model: fp_decode(c1, .., cd), fp_slice(axis, value, nodes), fp_corners(t1, .., td)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..plans.model import FunctionalTucker
from ..schema import coords


def register(spark: SparkSession, model: FunctionalTucker, suffix: str = "") -> None:
    """Registers the functions for one model; a suffix keeps several apart."""
    d = model.d

    def decode(*cols: pa.Array) -> pa.Array:
        x = [c.to_numpy(zero_copy_only=False).astype(float) for c in cols]
        bad = np.any([np.isnan(c) for c in x], axis=0)
        return pa.array(model.evaluate([np.nan_to_num(c) for c in x]), mask=bad)

    args = ", ".join(f"{c}: pa.Array" for c in coords(d))
    scope = {"pa": pa, "decode": decode}
    exec(f"def fp_decode({args}) -> pa.Array:\n    return decode({', '.join(coords(d))})", scope)  # an Arrow UDF takes a fixed number of arguments
    spark.udf.register(f"fp_decode{suffix}", F.arrow_udf(scope["fp_decode"], "double"))

    class Slice:
        def eval(self, axis: str, value: float, nodes: int):
            values = [np.array([float(value)]) if axis in (f"c{k + 1}", a.name) else np.linspace(a.lo, a.hi, nodes) for k, a in enumerate(model.axes)]
            x = model.core
            for k in range(d):
                x = np.moveaxis(np.tensordot(model.mode_values(k, values[k]), np.moveaxis(x, k, 0), axes=1), 0, k)
            for at, v in np.ndenumerate(x):
                yield (*[float(values[k][i]) for k, i in enumerate(at)], float(v))

    spark.udtf.register(f"fp_slice{suffix}", F.udtf(Slice, returnType=", ".join(f"{c} double" for c in (*coords(d), "u_hat"))))

    class Corners:
        def eval(self, *t):
            low = [int(np.floor(x)) for x in t]
            for e in range(2 ** len(t)):
                w, at = 1.0, []
                for k, x in enumerate(t):
                    b = e >> k & 1
                    f = x - low[k]
                    w *= f if b else 1 - f
                    at.append(low[k] + b)
                if w > 0:
                    yield (*at, w)

    spark.udtf.register(f"fp_corners{suffix}", F.udtf(Corners, returnType=", ".join(f"i{k + 1} int" for k in range(d)) + ", w double"))
