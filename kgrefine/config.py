"""Thresholds of all stages; every one is a parameter."""

from __future__ import annotations

import os
from dataclasses import dataclass, replace


@dataclass(frozen=True)
class Settings:
    # fixed values
    class_floor: float = 0.72
    class_floor_loose: float = 0.50
    centrality_weight: float = 0.4
    window_chars: int = 1500
    window_overlap: int = 300
    window_count: int = 4
    catalogue_tokens: int = 5000
    class_share: float = 0.7
    expand_from: float = 0.80
    expand_score: float = 0.78
    snap_floor: float = 0.80
    density_weight: int = 6
    variant_ratio: float = 0.85
    name_candidate: float = 0.75
    name_review: float = 0.90
    name_auto: float = 0.95
    resolve_auto: float = 0.85
    resolve_review: float = 0.60
    resolve_codename: float = 0.50
    neighbours: int = 20
    page_cover: float = 0.15
    page_chars: int = 50
    page_drawings: int = 200
    route_text: float = 0.80
    route_ocr: float = 0.20
    chunk_chars: int = 8000
    chunk_overlap: int = 1000
    chunk_pages: int = 5
    chunk_neighbours: int = 1
    gate_relations: int = 50
    gate_persons: int = 8
    gate_person_relations: int = 4
    gate_share: float = 0.30
    gate_types: int = 6
    fallback_entities: int = 20
    fallback_chars: int = 30_000
    batch_entities: int = 80
    batch_count: int = 8
    virtual_page_chars: int = 3600
    virtual_page_floor: int = 200
    title_token_chars: int = 12
    cache_minutes: int = 10
    breaker_seconds: int = 60
    workers: int = 4
    in_flight: int = 16
    embed_batch: int = 20
    embed_parallel: int = 5

    @classmethod
    def from_env(cls, **given) -> Settings:
        """Defaults, then the class floor from ``KGREFINE_CLASS_FLOOR`` where that is set, then ``given``."""
        floor = os.environ.get("KGREFINE_CLASS_FLOOR")
        base = cls() if floor is None else replace(cls(), class_floor=float(floor))
        return replace(base, **given)


DEFAULT = Settings()
