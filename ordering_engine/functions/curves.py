"""Space-filling curves in bit arithmetic."""

from __future__ import annotations

#: Shift and mask of each spreading step, for 16-bit coordinates.
SPREAD = ((8, 0x00FF00FF), (4, 0x0F0F0F0F), (2, 0x33333333), (1, 0x55555555))


def spread_sql(x: str, duck: bool) -> str:
    """Bits of a 16-bit number moved to the even places."""
    x = f"(cast({x} AS bigint) & 65535)"
    for shift, mask in SPREAD:
        moved = f"({x} << {shift})" if duck else f"shiftleft({x}, {shift})"
        x = f"(({x} | {moved}) & {mask})"
    return x


def morton_sql(x: str, y: str, duck: bool = False) -> str:
    odd = spread_sql(y, duck)
    return f"({spread_sql(x, duck)} | " + (f"({odd} << 1))" if duck else f"shiftleft({odd}, 1))")
