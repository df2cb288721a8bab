"""Path and label helpers."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from provgraph.schema import GENERATED, INFORMED, USED


def basename(path: Column) -> Column:
    return F.element_at(F.split(path, "/"), -1)


def short_path(path: Column, parts: int = 2) -> Column:
    return F.substring_index(path, "/", -parts)


def prov_label(op: Column) -> Column:
    """Stored label of an audited operation; null for operations that make no edge."""
    return F.when(op == "read", F.lit(USED)).when(op == "written", F.lit(GENERATED)).when(op == "spawned", F.lit(INFORMED))


def crosses(first_begin: Column, later_end: Column, strict: bool = False) -> Column:
    """Whether information that enters at ``first_begin`` can still leave before ``later_end``; null ends are open."""
    ok = first_begin < later_end if strict else first_begin <= later_end
    return F.coalesce(ok, F.lit(True))
