"""Settings of both sides in one place."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class PipelineConfig:
    directory_min: int = 1
    directory_max: int = 5
    depth_base: str | None = None  # with depth_levels: prefixes from this directory down
    depth_levels: int | None = None
    num_shards: int = 64
    kinds: tuple[str, ...] = ("user", "group", "dir")
    dir_filter: str | None = None
    quantiles: tuple[float, ...] = (0.10, 0.25, 0.50, 0.75, 0.90, 0.99)
    sketch: str = "dd"
    alpha: float = 0.01
    admins: tuple[str, ...] = ("group:admins",)
    request_bytes: int = 10 << 20
    request_wait_s: float = 5.0
    chunk_rows: int = 1_000_000
    max_events: int = 1000
    idle: str = "5 seconds"
    drop_ops: tuple[str, ...] = ("OPEN",)
    override: str = "batch"
    stat_mode: str = "call"
    max_dirs: int | None = None
    min_files: int = 100
    sink: str = "index"  # index, log or both
    mode: str = "batch"  # batch or stream

    def depth(self) -> tuple[int, int]:
        """Directory levels that become principals."""
        if self.depth_base is None:
            return self.directory_min, self.directory_max
        base = len([x for x in self.depth_base.split("/") if x])
        return base, base + (self.depth_levels if self.depth_levels is not None else 1)
