"""Label rows as one 64-bit number: 25 bits hub, 10 bits distance, 29 bits count."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Field widths.
HUB_BITS, DIST_BITS, COUNT_BITS = 25, 10, 29


def fits(hub: Column, dist: Column, paths: Column) -> Column:
    """Whether a row fits the fixed widths; others need the wide layout."""
    return (hub < (1 << HUB_BITS)) & (dist < (1 << DIST_BITS)) & (paths < (1 << COUNT_BITS))


def encode(hub: Column, dist: Column, paths: Column) -> Column:
    """The packed number; null where a field overflows."""
    packed = F.shiftleft(hub.cast("long"), DIST_BITS + COUNT_BITS).bitwiseOR(F.shiftleft(dist.cast("long"), COUNT_BITS)).bitwiseOR(paths.cast("long"))
    return F.when(fits(hub, dist, paths), packed)


def hub(code: Column) -> Column:
    return F.shiftrightunsigned(code, DIST_BITS + COUNT_BITS)


def dist(code: Column) -> Column:
    return F.shiftrightunsigned(code, COUNT_BITS).bitwiseAND(F.lit((1 << DIST_BITS) - 1)).cast("int")


def paths(code: Column) -> Column:
    return code.bitwiseAND(F.lit((1 << COUNT_BITS) - 1))


def product_sum(products: Column, kind: str = "long") -> Column:
    """Sum of path counts: 'long' raises on overflow, 'decimal' is exact to 38 digits, 'double' approximate."""
    return F.sum(products.cast({"long": "long", "decimal": "decimal(38,0)", "double": "double"}[kind]))
