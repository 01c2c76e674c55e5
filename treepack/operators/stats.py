"""Symbol counts and what follows from them."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treepack.plans import codebook as cb


def byte_histogram(stream: DataFrame, by: tuple[str, ...] = ("stream_id",), fraction: float | None = None, seed: int = 1) -> DataFrame:
    """(by.., sym, cnt). Each task counts its own batches, so at most 256 rows per group and batch are shuffled.

    fraction: of the values, chosen by a hash of their id, so the same ones each time.
    """
    if fraction is not None:
        stream = stream.where(F.pmod(F.xxhash64("value_id", F.lit(seed)), F.lit(1_000_000)) < int(fraction * 1_000_000))
    keys = list(by)
    names, kinds = [*keys, "sym", "cnt"], []

    def run(batches):
        held: dict[tuple, np.ndarray] = {}
        for b in batches:
            groups = zip(*(b.column(k).to_pylist() for k in keys), strict=True)
            for g, raw in zip(groups, b.column("raw").to_pylist(), strict=True):
                if raw:
                    held.setdefault(g, np.zeros(256, np.int64))
                    held[g] += np.bincount(np.frombuffer(raw, np.uint8), minlength=256)
            if len(held) > 4096:
                yield from _rows(held)
                held = {}
        yield from _rows(held)

    def _rows(held):
        out = [(*g, int(s), int(h[s])) for g, h in held.items() for s in np.flatnonzero(h)]
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)], names=names)

    from pyspark.sql.pandas.types import to_arrow_type

    schema = stream.select(*keys).schema
    kinds = [*(to_arrow_type(f.dataType) for f in schema.fields), pa.int32(), pa.int64()]
    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in schema.fields), "sym int", "cnt long"])
    return stream.select(*keys, "raw").mapInArrow(run, ddl).groupBy(*keys, "sym").agg(F.sum("cnt").alias("cnt"))


def byte_histogram_sql(stream: DataFrame, by: tuple[str, ...] = ("stream_id",)) -> DataFrame:
    """The same in built-in functions, one row per byte: for small data and as a reference."""
    pos = stream.where("octet_length(raw) > 0").select(*by, F.hex("raw").alias("h"), F.explode(F.expr("sequence(1, octet_length(raw))")).alias("i"))
    return pos.select(*by, F.expr("cast(conv(substring(h, 2 * i - 1, 2), 16, 10) as int)").alias("sym")).groupBy(*by, "sym").agg(F.count("*").alias("cnt"))


def codebooks(hist: DataFrame, by: tuple[str, ...] = ("stream_id",), max_len: int = cb.MAX_LEN, smooth: bool = False, method: str = "optimal", floor: int | None = None) -> DataFrame:
    """(by.., codebook_id, lengths binary(128)) from counts; each group has at most 256 rows.

    smooth: a code for every byte. floor: no count under this part of the total, which keeps rare symbols' codes short.
    """
    keys = list(by)
    fit = cb.fit_lengths if method == "optimal" else cb.repaired_lengths

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        counts = np.zeros(256, np.int64)
        counts[pdf["sym"].to_numpy()] = pdf["cnt"].to_numpy()
        if floor:
            counts = np.where(counts > 0, np.maximum(counts, counts.sum() // floor), 0)
        lengths = fit(cb.smoothed(counts) if smooth else counts, max_len)
        return pd.DataFrame({**{k: [pdf[k].iloc[0]] for k in keys}, "lengths": [cb.pack_lengths(lengths)]})

    ddl = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in hist.select(*keys).schema.fields), "lengths binary"])
    return hist.groupBy(*keys).applyInPandas(one, ddl).select(*keys, F.xxhash64("lengths").alias("codebook_id"), "lengths")


def code_lengths(books: DataFrame, by: tuple[str, ...] = ("stream_id",)) -> DataFrame:
    """(by.., sym, len) rows of packed length tables, in built-in functions."""
    pos = books.select(*by, F.hex("lengths").alias("h"), F.explode(F.sequence(F.lit(0), F.lit(255))).alias("sym"))
    digit = F.expr("substring(h, 2 * (sym div 2) + if(sym % 2 = 0, 2, 1), 1)")
    return pos.select(*by, "sym", F.conv(digit, 16, 10).cast("int").alias("len")).where("len > 0")


def canonical_codes(lens: DataFrame, by: tuple[str, ...] = ("stream_id",)) -> DataFrame:
    """(by.., sym, len, code) with code as a bit string: a running sum of code space, no loop. A group is one alphabet."""
    w = Window.partitionBy(*by).orderBy("len", "sym").rowsBetween(Window.unboundedPreceding, -1)
    before = F.coalesce(F.sum(F.expr("cast(shiftleft(1, 15 - len) as long)")).over(w), F.lit(0))
    return lens.withColumn("before", before).select(*by, "sym", "len", F.expr("lpad(bin(shiftright(before, 15 - len)), len, '0')").alias("code"))


def entropy_report(hist: DataFrame, codes: DataFrame) -> DataFrame:
    """(stream_id, symbols, n, h, l, efficiency, gap) in bits per symbol."""
    total = hist.groupBy("stream_id").agg(F.sum("cnt").alias("n"), F.count("*").alias("symbols"))
    each = hist.join(codes.select("stream_id", "sym", "len"), ["stream_id", "sym"]).join(total, "stream_id").withColumn("p", F.col("cnt") / F.col("n"))
    out = each.groupBy("stream_id").agg(F.first("symbols").alias("symbols"), F.first("n").alias("n"), F.sum(-F.col("p") * F.log2("p")).alias("h"), F.sum(F.col("p") * F.col("len")).alias("l"), F.min("len").alias("min_len"), F.max("len").alias("max_len"))
    return out.select("stream_id", "symbols", "n", F.round("h", 6).alias("h"), F.round("l", 6).alias("l"), F.round(F.col("h") / F.col("l"), 6).alias("efficiency"), F.round(F.col("l") - F.col("h"), 6).alias("gap"), "min_len", "max_len")
