"""The one-line patch of a script's import, as a column expression and for one text."""

from __future__ import annotations

import re

from pyspark.sql import Column
from pyspark.sql import functions as F

#: What scripts import, and what they get instead (own names).
OLD, NEW = "imaging", "reelspark.lift.shim_module"
_PLAIN = rf"(?m)^([ \t]*)import[ \t]+{OLD}[ \t]*(#.*)?$"
_ALIAS = rf"(?m)^([ \t]*)import[ \t]+{OLD}[ \t]+as[ \t]+(\w+)"


def patch_import(source: Column) -> Column:
    """Imports at the beginning of a line only: comments and strings in the middle of a line stay; a second patch changes nothing."""
    out = F.regexp_replace(source, _ALIAS, rf"$1import {NEW} as $2")
    return F.regexp_replace(out, _PLAIN, rf"$1import {NEW} as {OLD}")


def patched(source: str) -> str:
    out = re.sub(_ALIAS, rf"\1import {NEW} as \2", source)
    return re.sub(_PLAIN, rf"\1import {NEW} as {OLD}", out)
