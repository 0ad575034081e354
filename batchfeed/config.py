"""Parameters of the model. Times are integer microseconds, energies integer microjoules."""

from __future__ import annotations

from dataclasses import dataclass

HOUR_US = 3_600_000_000
DAY_US = 24 * HOUR_US
TICK_US = 100_000

#: Name, round-trip time in us.
REGIMES = (("local", 0), ("lan_fast", 50), ("lan", 100), ("lan_1", 1_000), ("lan_10", 10_000), ("wan", 30_000))
#: Node, role, site, has_gpu, n_gpus.
NODES = ((0, "compute", "site-1", True, 2), (1, "compute", "site-1", True, 2), (2, "compute", "site-2", True, 2), (3, "storage", "site-1", False, 0))


@dataclass(frozen=True)
class Feed:
    """Loader parameters: one set for all loaders, so that only the requests differ."""

    batch: int = 32
    workers: int = 2
    nodes: int = 2
    epochs: int = 2
    seed: int = 42
    header: int = 16
    net_bytes_s: int = 1_250_000_000
    disk_bytes_s: int = 500_000_000
    seek_us: int = 100
    pack_us: int = 200
    pack_ns_byte: int = 4
    decode_us: int = 100
    sample_rtts_permille: int = 1400
    pipeline_rtts_permille: int = 570
    read_bytes: int = 1 << 20
    hwm: int = 16
    depth: int = 4
    size_scale: int = 40
    step_us: int = 1_500


@dataclass(frozen=True)
class Power:
    """Watts when idle and added while busy, by component."""

    idle: tuple = (("cpu", 60), ("dram", 5), ("gpu", 60))
    busy: tuple = (("cpu", 5), ("dram", 2), ("gpu", 107))


MODEL_A = Power()
MODEL_B = Power(busy=(("cpu", 80), ("dram", 6), ("gpu", 180)))
FEED = Feed()
