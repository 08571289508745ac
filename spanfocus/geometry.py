"""Span geometry: sample length, span length, exclusions, strides, and what they cost."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Geometry:
    """How a sample is cut into spans and which span pairs are looked at.

    ``length`` tokens make ``length // span`` spans. Query rows are spans ``first_row``,
    ``first_row + col_stride``, ...; for row j the earlier spans ``skip_first``,
    ``skip_first + row_stride``, ... up to ``j - skip_near - 1`` are used.
    ``row_phase`` and ``col_phase`` shift the two strides (0 is the published setting).
    """

    length: int = 512
    span: int = 8
    skip_first: int = 1
    skip_near: int = 4
    row_stride: int = 4
    col_stride: int = 4
    first_row: int = 16
    row_phase: int = 0
    col_phase: int = 0

    def __post_init__(self) -> None:
        if self.span < 1 or self.length < self.span or self.length % self.span:
            raise ValueError("length must be a positive multiple of span")
        if min(self.row_stride, self.col_stride) < 1:
            raise ValueError("strides must be at least 1")
        if min(self.skip_first, self.skip_near, self.first_row, self.row_phase, self.col_phase) < 0:
            raise ValueError("exclusions, first row and phases must not be negative")

    @property
    def n_spans(self) -> int:
        return self.length // self.span

    def rows(self) -> list[int]:
        """Indices j of the query spans."""
        return list(range(self.first_row + self.col_phase, self.n_spans, self.col_stride))

    def cols(self, j: int) -> list[int]:
        """Indices i of the earlier spans that row j uses; may be empty."""
        return list(range(self.skip_first + self.row_phase, j - self.skip_near, self.row_stride))

    def with_strides(self, row_stride: int, col_stride: int) -> Geometry:
        return replace(self, row_stride=row_stride, col_stride=col_stride)

    @classmethod
    def named(cls, profile: str) -> Geometry:
        try:
            return PROFILES[profile]
        except KeyError:
            raise ValueError(f"unknown profile {profile!r}; known: {', '.join(PROFILES)}") from None


PROFILES = {
    "paper": Geometry(32768, 128, 1, 4, 4, 4, 16),
    "desk": Geometry(512, 8, 1, 4, 4, 4, 16),
    "desk-wide": Geometry(1024, 4, 1, 4, 4, 4, 16),
    "smoke": Geometry(256, 8, 1, 2, 2, 2, 8),
    "vectors": Geometry(40, 2, 1, 2, 2, 2, 6),
}


def cost_of(geometry: Geometry) -> dict[str, int]:
    """Query rows, span pairs and attention logits of one sample (every key is needed by a row's softmax)."""
    rows = geometry.rows()
    return {
        "rows": len(rows),
        "pairs": sum(len(geometry.cols(j)) for j in rows),
        "logits": sum((j + 1) * geometry.span**2 for j in rows),
    }
