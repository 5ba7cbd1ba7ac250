"""One hash that every engine computes alike: 60 bits of md5 as a bigint.  All random choices use it."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def portable_hash(*parts) -> Column:
    """Hash of the parts joined by ``|``; strings in ``parts`` are literals, columns are cast to text."""
    text = F.concat_ws("|", *[p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def portable_hash_py(*parts) -> int:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def sql_hash(*parts: str) -> str:
    """The same in the oracle's SQL; each part is an SQL expression, literals in quotes."""
    return "CAST(('0x' || substr(md5(concat_ws('|', " + ", ".join(parts) + ")), 1, 15)) AS BIGINT)"
