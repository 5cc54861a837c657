"""Convolutions over dense indices as stencils on tiles.

The image is cut in tiles of output positions. A cell goes to every tile that some kernel offset takes it to, its own
and at the rims its neighbours' (the halo), in one exchange by tile; the products and sums of a tile then need no
further exchange, where the general evaluators deal partial sums by position.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.operators.relation import AnnotatedRelation

#: Side of a tile, and weights that a kernel may hold to be broadcast.
TILE, KERNEL_ROWS = 64, 100_000


def convolve(image: AnnotatedRelation, kernel: AnnotatedRelation, shared: int = 0, filters: int = 0, channels: int = 0, tile: int = TILE) -> DataFrame:
    """(h0, ..., ann): sums over offsets of image x kernel, for the query
    Q(shared, filters, positions) <- image(shared, channels, positions + offsets) * kernel(filters, channels, offsets).

    The first `shared` columns of the image (a batch) are left as they are, the next `channels` are summed over with
    the kernel's, the others are positions; the kernel's first columns are filters. A kernel beyond KERNEL_ROWS rows is
    an error: it is no stencil. Positions are the image's less an offset, so they may lie outside the image.
    """
    s, dims = image.semiring, image.arity - shared - channels
    if kernel.arity != filters + channels + dims:
        raise ValueError("image and kernel do not fit together")
    weights = kernel.df.limit(KERNEL_ROWS + 1).collect()
    if len(weights) > KERNEL_ROWS:
        raise ValueError(f"the kernel has more than {KERNEL_ROWS} weights")
    spark, at = image.df.sparkSession, filters + channels
    names = [f"f{i}" for i in range(filters)] + [f"m{i}" for i in range(channels)] + [f"o{i}" for i in range(dims)]
    stencil = spark.createDataFrame(weights, kernel.df.schema).toDF(*names, "w")
    lows = [min((r[at + i] for r in weights), default=0) for i in range(dims)]
    highs = [max((r[at + i] for r in weights), default=0) for i in range(dims)]
    positions = [F.col(f"c{shared + channels + i}") for i in range(dims)]
    tiles = image.df
    for i, p in enumerate(positions):  # positions p - high, ..., p - low fall in these tiles
        tiles = tiles.withColumn(f"_t{i}", F.explode(F.sequence(F.floor((p - highs[i]) / tile), F.floor((p - lows[i]) / tile))))
    group = [*(f"c{i}" for i in range(shared)), *(f"_t{i}" for i in range(dims))]
    dealt = tiles.repartition(*group)
    on = [F.col(f"c{shared + i}") == F.col(f"m{i}") for i in range(channels)]
    both = dealt.join(F.broadcast(stencil), on) if on else dealt.crossJoin(F.broadcast(stencil))
    out = [(p - F.col(f"o{i}")).alias(f"p{i}") for i, p in enumerate(positions)]
    made = both.select(*group, *(f"f{i}" for i in range(filters)), *out, s.times(F.col("ann"), F.col("w")).alias("ann"))
    for i in range(dims):  # of the halo, what belongs to this tile
        made = made.where(F.floor(F.col(f"p{i}") / tile) == F.col(f"_t{i}"))
    keys = [*group, *(f"f{i}" for i in range(filters)), *(f"p{i}" for i in range(dims))]
    summed = s.group(made, keys)
    heads = [*(f"c{i}" for i in range(shared)), *(f"f{i}" for i in range(filters)), *(f"p{i}" for i in range(dims))]
    return summed.select(*(F.col(c).alias(f"h{i}") for i, c in enumerate(heads)), "ann")
