"""One portable hash as a Column, as SQL text and in Python: the first hex digits of an md5.

xxhash64 is the faster choice where no other engine has to agree; ``fast`` switches to it.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F

SALT = 1


def hash32(*parts: Column | str, salt: int = SALT, fast: bool = False) -> Column:
    cols = [F.col(p) if isinstance(p, str) else p for p in parts]
    if fast:
        return F.shiftrightunsigned(F.xxhash64(*cols, F.lit(salt)), 32)
    return F.conv(F.substring(F.md5(F.concat_ws(":", *[c.cast("string") for c in cols], F.lit(str(salt)))), 1, 8), 16, 10).cast("long")


def hash32_sql(*parts: str, salt: int = SALT) -> str:
    return f"CAST(('0x' || substr(md5(concat_ws(':', {', '.join(f'CAST({p} AS VARCHAR)' for p in parts)}, '{salt}')), 1, 8)) AS BIGINT)"


def hash32_py(*parts: int, salt: int = SALT) -> int:
    return int(hashlib.md5(":".join([*map(str, parts), str(salt)]).encode()).hexdigest()[:8], 16)


def text_id(text: Column) -> Column:
    """56-bit id of a string."""
    return F.conv(F.substring(F.md5(text), 1, 14), 16, 10).cast("long")


def text_id_sql(text: str) -> str:
    return f"CAST(('0x' || substr(md5({text}), 1, 14)) AS BIGINT)"
