"""The codec of uniform tracks by DataFrame functions alone, down to the container's bytes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spectrack.functions import numbers as N
from spectrack.functions import track as K
from spectrack.functions.params import CodecParams
from spectrack.operators import blocks as B


def bit_text(u: Column, l: int, elide: bool = False) -> Column:  # noqa: E741
    """The bits of an unsigned number's code as text: low chunk first, each behind a flag that more follow."""
    digits = F.bin(u)
    n = F.ceil(F.length(digits) / l).cast("int")
    padded = F.lpad(digits, n * l, "0")
    chunks = F.transform(F.sequence(F.lit(1), n), lambda i: F.concat(F.when(i < n, "1").otherwise("0"), F.substring(padded, (n - i) * l + 1, F.lit(l))))
    whole = F.array_join(chunks, "")
    return F.substring(whole, F.lit(1), F.length(whole) - 1) if elide else whole


def _all(codes: Column, l: int, elide: bool = False) -> Column:  # noqa: E741
    return F.array_join(F.transform(codes, lambda u: bit_text(u, l, elide)), "")


def _in_order(*by: str, value: str = "code") -> Column:
    """The values of a group, ordered by the columns."""
    return F.transform(F.array_sort(F.collect_list(F.struct(*by, value))), lambda x: x[value])


def to_bytes(bits: Column) -> Column:
    """Text of bits as bytes, the last one filled with zeros."""
    filled = F.rpad(bits, (F.ceil(F.length(bits) / 8) * 8).cast("int"), "0")
    nibbles = F.transform(F.sequence(F.lit(1), F.length(filled), F.lit(4)), lambda i: F.conv(F.substring(filled, i, F.lit(4)), 2, 16))
    return F.unhex(F.array_join(nibbles, ""))


def compress(points: DataFrame, p: CodecParams, step: int, dim: int) -> DataFrame:
    """track_id, n, n_corr, payload of tracks sampled every `step` microseconds from time 0 on, of three samples or more: byte for byte the
    container of the Arrow engine. Velocities in blocks, the transform by a join with its basis, integers, decoding,
    corrections and bits are all columns, so every step can be looked at; the Arrow engine is the fast one."""
    if p.positions or not p.blocks or not p.validate or p.integer_input or p.ends != "closed" or p.eps_t != 1:
        raise ValueError("the expression engine knows the codec itself and none of its ablations")
    signal = B.axes(B.from_clock(points, step))
    coded = B.trimmed(B.codes(B.coefficients(B.velocities(signal, p.b_s), p.b_s, p.r_ret), p.eps_f))
    # blocks of one velocity, or with nothing kept, have no codes
    every = B.block_ends(signal, p.b_s, p.eps_p, dim).select("track_id", "block_id", "axis", F.col("code").alias("end"))
    parts = every.join(coded.select("track_id", "block_id", "axis", "codes"), ["track_id", "block_id", "axis"], "left").withColumn("codes", F.coalesce("codes", F.array().cast("array<bigint>")))
    parts = parts.groupBy("track_id").agg(_in_order("block_id", "axis", value="end").alias("ends"), _in_order("block_id", "axis", value="codes").alias("codes"))
    first = B.anchors(signal, p.eps_p).groupBy("track_id").agg(_in_order("axis", value="anchor").alias("anchors"))
    decoded = B.reconstructed(signal, p.b_s, p.eps_f, p.eps_p, dim, p.r_ret)
    fixes = B.corrections(decoded, p.eps, p.eps_p, dim).withColumn("t", F.col("j") * step)
    fixes = fixes.groupBy("track_id").agg(_in_order("t", "axis").alias("fixes"), F.array_sort(F.collect_set("t")).alias("fix_t"))
    spans = points.groupBy("track_id").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("t0"))
    rows = spans.filter("n > 2").join(parts, "track_id").join(first, "track_id").join(fixes, "track_id", "left")
    empty = F.array().cast("array<bigint>")
    rows = rows.withColumn("fixes", F.coalesce("fixes", empty)).withColumn("fix_t", F.coalesce("fix_t", empty))
    steps = F.transform("fix_t", lambda t, i: t - F.when(i == 0, 0).otherwise(F.get(F.col("fix_t"), i - 1)))
    l, elide = p.l, p.zero_free and p.l_freq == 1  # noqa: E741
    flat, signed = F.flatten("codes"), N.zz1 if p.zero_free else N.zz
    bits = F.concat(
        bit_text(F.lit(step), l), bit_text(F.lit(1), l),  # interval, fragments
        bit_text(F.lit(0), l),  # outliers
        bit_text(F.size("fix_t").cast("long"), l), _all(F.transform(steps, N.zz), l), _all(F.transform("fixes", N.zz1), l),
        bit_text(N.zz(F.col("t0")), l), bit_text(F.col("n"), l),
        _all(F.transform("anchors", N.zz), l), _all(F.transform("ends", N.zz), l), _all(F.transform("codes", lambda c: F.size(c).cast("long")), l),
        _all(F.transform(flat, signed), p.l_freq, elide),
    )
    none = K.np.zeros((0, dim), K.np.int64)
    head = K.head(K.Encoded(dim, step, *[none] * 10, uniform=True), p)
    return rows.select("track_id", "n", F.size("fix_t").cast("long").alias("n_corr"), F.concat(F.lit(head), to_bytes(bits)).alias("payload"))
