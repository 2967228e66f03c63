"""Radix sort of a whole table by digits of several bits: one exchange per digit instead of one per bit.

Each pass is stable: a row's new position is the number of rows with smaller digits, plus rows of its
digit in earlier blocks, plus its rank among its block's. Counts per block and digit are summed over a
tree; blocks are ranges of positions of fixed size.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..core.position import POS, beside, prefix_sums
from ..core.session import checkpointed


def radix_sort(df: DataFrame, key: str, bits: int | None = None, digit_bits: int = 8, block_rows: int = 1 << 16, pos: str = POS) -> DataFrame:
    """``df`` has dense positions ``pos``; returns it with positions in stable order of the non-negative key.

    bits: of the largest key; None: taken from the data. Keys below zero or of more bits raise an error.
    """
    low, high = df.agg(F.min(key), F.max(key)).first()
    need = int(high or 0).bit_length()
    bits = need if bits is None else bits
    if (low or 0) < 0 or need > bits:
        raise ValueError(f"keys from {low} to {high} do not fit {bits} bits")
    last = df.agg(F.max(pos)).first()[0]
    blocks = 0 if last is None else int(last) // block_rows + 1
    for low in range(0, bits, digit_bits):
        width = min(digit_bits, bits - low)
        digit = F.shiftright(F.col(key), low).bitwiseAND((1 << width) - 1)
        # cells in the order of their rows' new places: by digit, then by block
        marked = df.withColumn("__cell", (digit.cast("long") * blocks + F.floor(F.col(pos) / block_rows)).cast("long"))
        counts = marked.groupBy("__cell").agg(F.count("*").alias("__n"))
        rank = F.row_number().over(Window.partitionBy("__cell").orderBy(pos)) - 1
        cells = blocks << width
        met = beside(marked.withColumn("__r", rank), prefix_sums(counts, "__cell", "__n", cells), ["__cell"], cells)
        df = checkpointed(met.withColumn(pos, (F.col("__before") + F.col("__r")).cast("long")).drop("__cell", "__before", "__r"))
    return df
