"""Detector settings and presets."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class DetectorConfig:
    """Settings of one detection run.

    The defaults are the published ones: modified LCS on locality-sensitive codes, equal and one-node paths merged,
    sets of up to 1.7 times the size, paths of up to 7 nodes more. ``normalise`` is ``longer`` (distance over the longer path) or ``none`` (absolute). ``tie`` says how two
    sets of equal size are oriented: ``min`` of both directions, or ``first``. ``copy`` is ``lossless`` (classes of
    equal sets are matched once and results copied), ``lossy`` (not copied) or ``off``.
    """

    tau: float = 0.3
    min_lines: int = 15
    metric: str = "lcs_mod"
    encoding: str = "lsh"
    merge: str = "one_node"
    max_set_factor: float | None = 1.7
    max_len_diff: int | None = 7
    copy: str = "lossless"
    normalise: str = "longer"
    tie: str = "min"
    sub_slack: float = 0.10
    sub_min_len: int = 10
    candidates: str = "prefix"

    def but(self, **changes) -> DetectorConfig:
        return replace(self, **changes)

    @classmethod
    def default(cls) -> DetectorConfig:
        return cls()

    @classmethod
    def plain(cls) -> DetectorConfig:
        """Modified LCS on MD5 codes, only equal paths merged and no cap on lengths: the base that metrics and encodings are compared on."""
        return cls(encoding="md5", merge="identical", max_len_diff=None)

    @classmethod
    def fast(cls) -> DetectorConfig:
        """Hamming on MD5 codes."""
        return cls(metric="hamming", encoding="md5")

    @classmethod
    def legacy(cls) -> DetectorConfig:
        """Plain LCS on 4-byte codes."""
        return cls(metric="lcs", encoding="prime4")

    @classmethod
    def stack_ir(cls) -> DetectorConfig:
        return cls(metric="lcs", encoding="prime4", tau=0.15)

    @classmethod
    def register_ir(cls) -> DetectorConfig:
        return cls(metric="lcs", encoding="prime4", tau=0.3)
