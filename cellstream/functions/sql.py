"""SQL surface: functions and table functions registered on a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def register(spark: SparkSession, schedule=None) -> None:
    """gaussian_bits(p, left, mu, sigma), huffman_bits(count), count_bits(p), expand_points(TABLE), decode_cells(TABLE).

    With a schedule also count_tree_agg(key), the codestream of a group of keys as one BINARY, and tile_decode(TABLE), whose rows
    (n, payload) come back as (n, prefix, cnt).
    """

    @F.pandas_udf("double")
    def gaussian_bits(p: pd.Series, left: pd.Series, mu: pd.Series, sigma: pd.Series) -> pd.Series:
        import numpy as np

        out = []
        for n, x, m, s in zip(p, left, mu, sigma, strict=True):
            k = np.arange(int(n) + 1)
            w = np.exp(-(((k - m) / s) ** 2) / 2)
            out.append(-np.log2(w[int(x)] / w.sum()))
        return pd.Series(out)

    @F.pandas_udf("long")
    def huffman_bits(counts: pd.Series) -> int:
        from ..operators.baselines import huffman_lengths

        return int(sum(a * b for a, b in zip(huffman_lengths(counts.tolist()), counts, strict=True)))

    class ExpandPoints:
        def eval(self, row: T.Row):
            for i in range(1, row["cnt"] + 1):
                yield row["level"], row["prefix"], i

    class DecodeCells:
        """Children of one wave's nodes: (level, prefix, cnt) rows from (level, prefix, cnt, left_cnt)."""

        def eval(self, row: T.Row):
            for half, n in ((0, row["left_cnt"]), (1, row["cnt"] - row["left_cnt"])):
                if n:
                    yield row["level"] + 1, 2 * row["prefix"] + half, n

    if schedule is not None:

        @F.pandas_udf("binary")
        def count_tree_agg(key: pd.Series) -> bytes:
            """Many small sets, a payload each: one tile with all its waves."""
            import numpy as np

            from ..operators.stream_codec import BandEncoder

            coder = BandEncoder()
            keys, m = np.unique(key.to_numpy(np.int64), return_counts=True)
            for level in range(schedule.q):
                prefix = keys >> (schedule.q - level)
                starts = np.flatnonzero(np.concatenate([[True], prefix[1:] != prefix[:-1]]))
                low = np.where(keys >> (schedule.q - level - 1) & 1, 0, m)
                coder.put(prefix[starts], np.add.reduceat(m, starts), np.add.reduceat(low, starts), level, schedule, 0)
            return coder.finish()

        class TileDecode:
            def eval(self, row: T.Row):
                import numpy as np

                from ..operators.stream_codec import decode_bands

                start = np.zeros(1, np.int64), np.array([row["n"]], np.int64)
                prefix, cnt = decode_bands([(0, schedule.q, bytes(row["payload"]))], *start, 0, schedule.q, schedule, [0] * schedule.q)
                for p, c in zip(prefix.tolist(), cnt.tolist(), strict=True):
                    yield row["n"], p, c

        spark.udf.register("count_tree_agg", count_tree_agg)
        spark.udtf.register("tile_decode", F.udtf(TileDecode, returnType="n long, prefix long, cnt long"))
    spark.udf.register("gaussian_bits", gaussian_bits)
    spark.udf.register("huffman_bits", huffman_bits)
    spark.udtf.register("expand_points", F.udtf(ExpandPoints, returnType="level int, prefix long, i long"))
    spark.udtf.register("decode_cells", F.udtf(DecodeCells, returnType="level int, prefix long, cnt long"))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION count_bits(p BIGINT) RETURNS DOUBLE RETURN log2(p + 1)")
