"""What is to be ranked and by which access path."""

from __future__ import annotations

from dataclasses import dataclass, field

KINDS = ("score_each", "score_batch", "pivot_split", "slide_window", "run_merge")
NULLS = ("last", "first", "error")


@dataclass(frozen=True)
class PathConfig:
    """One access path: a kind and its numbers. ``lookup`` grounds value paths in facts."""

    kind: str
    m: int = 4
    v: int = 1
    lookup: bool = False
    max_point: int = 10
    pivot: str = "first"
    rescan: bool = False
    stop_when_stable: bool = False
    peer_override: bool = True

    def __post_init__(self) -> None:
        if self.kind not in KINDS:
            raise ValueError(f"no access path {self.kind!r}; there are {', '.join(KINDS)}")
        if self.kind in ("score_batch", "run_merge") and self.m < 1 or self.kind in ("slide_window", "run_merge") and self.m < 2:
            raise ValueError(f"{self.kind} needs a larger m than {self.m}")
        if self.v < 1:
            raise ValueError("at least one vote")
        if self.pivot not in ("first", "random", "median3"):
            raise ValueError(f"no pivot rule {self.pivot!r}")
        if self.lookup and not self.kind.startswith("score"):
            raise ValueError("only value paths can look facts up")

    @property
    def path_id(self) -> str:
        name = {
            "score_each": "point", "score_batch": f"ext_point_{self.m}", "pivot_split": "quick" if self.v == 1 else f"quick_{self.v}",
            "slide_window": f"ext_bubble_{self.m}", "run_merge": f"ext_merge_{self.m}",
        }[self.kind]
        return name + "_search" * self.lookup


POINT, EXT_POINT = PathConfig("score_each"), PathConfig("score_batch")
POINT_SEARCH, EXT_POINT_SEARCH = PathConfig("score_each", lookup=True), PathConfig("score_batch", lookup=True)
QUICK, QUICK_3 = PathConfig("pivot_split"), PathConfig("pivot_split", v=3)
EXT_BUBBLE, EXT_MERGE = PathConfig("slide_window"), PathConfig("run_merge")


def candidate_grid(ms: tuple[int, ...] = (4,), vs: tuple[int, ...] = (1, 3), lookup: bool = False) -> list[PathConfig]:
    """All families with every m and v; with ``lookup`` the grounded value paths too."""
    out = [POINT, *[PathConfig("score_batch", m=m) for m in ms], *[PathConfig("pivot_split", v=v) for v in vs]]
    out += [PathConfig(kind, m=m) for kind in ("slide_window", "run_merge") for m in ms if m > 1]
    if lookup:
        out += [POINT_SEARCH, *[PathConfig("score_batch", m=m, lookup=True) for m in ms]]
    return out


@dataclass(frozen=True)
class RankSpec:
    """An ordering by a criterion in words."""

    criterion: str
    descending: bool = True
    limit: int | None = None
    nulls: str = "last"
    kind: str = "reasoning"
    partition_by: tuple[str, ...] = field(default_factory=tuple)

    def __post_init__(self) -> None:
        if not self.criterion.strip():
            raise ValueError("an ordering needs a criterion")
        if self.limit is not None and self.limit < 0:
            raise ValueError("LIMIT can't be negative")
        if self.nulls not in NULLS:
            raise ValueError(f"nulls is one of {', '.join(NULLS)}")
