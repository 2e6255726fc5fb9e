"""Thresholds of the track pipeline in one frozen object."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class PipelineConfig:
    mime_token: str = "xhtml"
    ext: str = "html"
    max_tracks: int = 1
    min_len_m: float = 500.0
    max_len_m: float = 100_000.0
    min_points_per_100m: float = 1.0
    desc_min: int = 50
    desc_max: int = 2000
    lang_more_than: int = 5
    circular_m: float = 350.0
    earth_radius_m: float = 6_371_000.0
    quality_in_doubt: bool = False
    privacy_in_doubt: bool = True
    coalesce_gap: int = 4096
    axis: str = "latlon"


DEFAULT = PipelineConfig()
