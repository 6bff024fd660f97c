"""Parameters of a detection run, with the published defaults."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class DetectConfig:
    """Percentages are whole numbers, so filters never compare floating point values.

    mit: fewest tokens of a fragment; gamma_pct, theta_pct: size and action thresholds; element: ``bag``,
    ``pair``, ``set`` or ``action+pair`` (``pair`` for all that share an action); denom: ``min``, ``max``, ``query``, ``union`` or ``count``; layout: ``geometric``,
    ``count`` or ``none`` with ``k`` bands; exact_size: also test each pair's sizes; sub_bands: second
    level of size parts; prefix: ``auto``, ``on`` or ``off``; collapse: join representatives of equal
    fragments only; cut: probability above which a pair is reported; symmetry: ``concat`` or ``average``.
    """

    mit: int = 15
    min_lines: int | None = None
    gamma_pct: int = 60
    theta_pct: int = 55
    inclusive: bool = False
    element: str = "bag"
    denom: str = "min"
    layout: str = "geometric"
    k: int = 6
    exact_size: bool = True
    sub_bands: int = 4
    prefix: str = "auto"
    collapse: bool = True
    cut: float = 0.5
    symmetry: str = "concat"

    def __post_init__(self) -> None:
        if self.element not in ("bag", "pair", "set", "action+pair") or self.denom not in ("min", "max", "query", "union", "count"):
            raise ValueError("unknown element or denominator")
        if self.layout not in ("geometric", "count", "none") or self.prefix not in ("auto", "on", "off"):
            raise ValueError("unknown layout or prefix mode")
        if not (0 < self.gamma_pct <= 100 and 0 <= self.theta_pct <= 100):
            raise ValueError("percentages are 1..100 (gamma) and 0..100 (theta)")


#: Names of the 24 metrics, in the order of the vector.
METRICS = (
    "xmet", "vref", "vdec", "nos", "nopr", "noa", "nexp", "nand", "mdn", "loop", "lmet", "hvoc",
    "hdif", "heff", "exct", "excr", "cref", "comp", "cast", "nbltrl", "ncltrl", "nsltrl", "nnltrl", "nnulltrl",
)

#: Whole numbers that fix all 24 metrics: the counts and the four Halstead bases.
BASES = tuple(m for m in METRICS if m not in ("hvoc", "hdif", "heff")) + ("op_kinds", "operand_kinds")
