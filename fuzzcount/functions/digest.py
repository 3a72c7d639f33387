"""Numbers drawn from text keys: the same in every engine, on every retry and in every partition."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def num(text: Column) -> Column:
    """The first eight hex digits of a text's md5 as an integer below 2^32."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("bigint")


def keyed(*parts: Column | str | int) -> Column:
    """Parts joined by a bar; plain values are literals."""
    return F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts))


def below(share: float) -> int:
    """The bound under which `num` falls with the given probability."""
    return int(share * 2**32)
