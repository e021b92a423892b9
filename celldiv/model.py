"""What a microdata table is: quasi-identifier columns, one sensitive column, a row id."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class Infeasible(ValueError):
    """The table has no diverse release: one sensitive value is too frequent."""


@dataclass(frozen=True)
class MicrodataSpec:
    """qi and sa name columns; domains (sizes by QI) default to what the data has; taxonomies map a QI to paths from leaf value to root."""

    qi: tuple[str, ...]
    sa: str
    row_id: str = "row_id"
    domains: dict[str, int] = field(default_factory=dict)

    def project(self, qi: tuple[str, ...]) -> MicrodataSpec:
        return MicrodataSpec(tuple(qi), self.sa, self.row_id, self.domains)

    def cell(self) -> Column:
        """The QI tuple; a null is an ordinary value in it."""
        return F.struct(*self.qi)


def check_l(l: int) -> int:
    if l < 2:
        raise ValueError("l must be 2 or more")
    return l


#: Names that releases add.
RESERVED = {"cell", "sa", "h", "moved", "in_residue", "cell_id", "star_mask"}


def shown(df: DataFrame, spec: MicrodataSpec) -> DataFrame:
    """The columns a release needs, and no others."""
    if clash := RESERVED & {*spec.qi, spec.row_id} | {"in_residue", "cell_id", "star_mask"} & {spec.sa}:
        raise ValueError(f"rename the columns {sorted(clash)}: releases add columns of these names")
    return df.select(*spec.qi, spec.sa, spec.row_id)
