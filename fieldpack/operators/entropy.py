"""Huffman coding of code indices."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def symbol_freq(codes: DataFrame, symbol: str = "code", by: tuple[str, ...] = ()) -> DataFrame:
    """by..., symbol, freq."""
    return codes.where(F.col(symbol).isNotNull()).groupBy(*by, F.col(symbol).cast("int").alias("symbol")).agg(F.count("*").alias("freq"))


def entropy(freq: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """by..., symbols, total, entropy in bits per symbol."""
    sums = freq.groupBy(*by).agg(F.count("*").alias("symbols"), F.sum("freq").alias("total"), F.sum(F.col("freq") * F.log2(F.col("freq").cast("double"))).alias("_s"))
    return sums.select(*by, "symbols", "total", (F.log2(F.col("total").cast("double")) - F.col("_s") / F.col("total")).alias("entropy"))


def code_lengths(freq: dict[int, int]) -> dict[int, int]:
    """Huffman lengths; a single symbol gets 1 bit. Ties: smaller weight, then the group with the smaller symbol."""
    if len(freq) == 1:
        return {next(iter(freq)): 1}
    heap = [(f, s, [s]) for s, f in sorted(freq.items())]
    heapq.heapify(heap)
    length = dict.fromkeys(freq, 0)
    while len(heap) > 1:
        a, b = heapq.heappop(heap), heapq.heappop(heap)
        for s in a[2] + b[2]:
            length[s] += 1
        heapq.heappush(heap, (a[0] + b[0], min(a[1], b[1]), a[2] + b[2]))
    return length


def canonical(length: dict[int, int]) -> dict[int, str]:
    """Canonical codes: by length, then symbol."""
    out, code, last = {}, 0, 0
    for s, n in sorted(length.items(), key=lambda x: (x[1], x[0])):
        code <<= n - last
        out[s] = format(code, f"0{n}b")
        code, last = code + 1, n
    return out


def huffman_table(freq: DataFrame, grp: str = "all") -> DataFrame:
    """grp, symbol, freq, len, code. The alphabet is at most the codebook's size, so its counts go to the driver."""
    counts = {r["symbol"]: r["freq"] for r in freq.select("symbol", "freq").collect()}
    codes = canonical(code_lengths(counts)) if counts else {}
    rows = [(grp, s, int(f), len(codes[s]), codes[s]) for s, f in sorted(counts.items())]
    return freq.sparkSession.createDataFrame(rows, "grp string, symbol int, freq long, len int, code string")


def coded_bits(table: DataFrame) -> DataFrame:
    """grp, bits, symbols."""
    return table.groupBy("grp").agg(F.sum(F.col("freq") * F.col("len")).alias("bits"), F.sum("freq").alias("symbols"))


def pack_symbols(symbols: np.ndarray, codes: dict[int, str]) -> bytes:
    bits = "".join(codes[int(s)] for s in symbols)
    return int(bits + "0" * (-len(bits) % 8), 2).to_bytes((len(bits) + 7) // 8, "big") if bits else b""


def unpack_symbols(data: bytes, codes: dict[int, str], n: int) -> list[int]:
    back, out, word = {c: s for s, c in codes.items()}, [], ""
    for byte in data:
        for bit in format(byte, "08b"):
            if len(out) == n:
                return out
            word += bit
            if word in back:
                out.append(back[word])
                word = ""
    if len(out) < n:
        raise ValueError(f"{n} symbols were announced, {len(out)} found")
    return out


def huffman_encode(symbols: Column, codes: dict[int, str]) -> Column:
    """An array of symbols as binary."""

    @F.pandas_udf("binary")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for col in batches:
            yield pd.Series([pack_symbols(np.asarray(x), codes) for x in col], dtype=object)

    return run(symbols)


def huffman_decode(data: Column, codes: dict[int, str], n: Column) -> Column:
    @F.pandas_udf("array<int>")
    def run(col: pd.Series, counts: pd.Series) -> pd.Series:
        return pd.Series([unpack_symbols(bytes(x), codes, int(k)) for x, k in zip(col, counts)], dtype=object)

    return run(data, n)
