"""Which kernel, exchange and storage a run uses, decided from sizes."""

from __future__ import annotations

MB = 1 << 20
#: Sums of a generated aggregation stay below Spark's codegen field limit up to this width.
WIDEST_SQL = 12
#: Largest table of numbers that is broadcast as a whole, all tiles of a slice together, and what the driver may hold.
BROADCAST_MB, TILES_MB, DRIVER_MB = 256, 4096, 1024
#: Largest slices that go through the driver as they are; larger broadcasts are packed.
PLAIN_MB = 2
#: Most rows of a slice that the driver holds row by row: each takes it some hundred bytes there, however few its numbers.
PLAIN_ROWS = 1 << 14


def fits_broadcast(rows: int, numbers: int, limit_mb: int = BROADCAST_MB) -> bool:
    """Whether so many rows of so many 8-byte numbers may be broadcast."""
    return 8 * rows * numbers <= limit_mb * MB


def broadcast_form(rows: int, numbers: int) -> bool | str:
    """How so many rows of so many 8-byte numbers are joined: broadcast as they are, packed, or by a shuffle."""
    return (rows <= PLAIN_ROWS and fits_broadcast(rows, numbers, PLAIN_MB)) or ("packed" if fits_broadcast(rows, numbers) else False)


def fits_driver(rows: int, numbers: int, limit_mb: int = DRIVER_MB) -> bool:
    return 8 * rows * numbers <= limit_mb * MB


def choose_kernel(width: int, kernel: str = "auto") -> str:
    """`sql` keeps the normal equations in generated code; `arrow` sums them in batches."""
    return ("sql" if width <= WIDEST_SQL else "arrow") if kernel == "auto" else kernel


def choose_exchange(dims: list[int], width: int, exchange: str = "auto", driver_mb: int = PLAIN_MB, broadcast_mb: int = BROADCAST_MB, tiles_mb: int = TILES_MB) -> str:
    """How updated rows reach all machines: through the driver while small, as a written table that is broadcast up
    to `broadcast_mb`, in several broadcast tiles up to `tiles_mb` (what a machine must hold of a group's slices),
    else joined with a shuffle. Only the last one moves cells."""
    if exchange != "auto":
        return exchange
    size = 8 * width * sum(dims)
    return "broadcast" if size <= driver_mb * MB else "dfs" if size <= broadcast_mb * MB else "tiles" if size <= tiles_mb * MB else "join"


def tile_count(dims: list[int], width: int, limit_mb: int = BROADCAST_MB) -> int:
    """Tiles that keep each broadcast of the longest mode's slice within the limit; two at least."""
    return max(2, -(-8 * (width + 1) * max(dims) // (limit_mb * MB)))


def choose_storage(cells: int, dims: list[int], machines: int, disk_bytes: float = float("inf"), storage: str = "auto") -> str:
    """Copies per mode if the disk holds them and every mode has rows enough for its machines, else one copy."""
    if storage != "auto":
        return storage
    copies = cells * len(dims) * (8 * len(dims) + 16)
    return "mode_copies" if copies <= disk_bytes and min(dims) >= 4 * machines else "single"
