"""Choices between physical forms of one computation, by stated sizes."""

from __future__ import annotations

#: Owners up to which members' vectors come to the driver, and bytes of vectors at most.
DRIVER_CLIENTS, DRIVER_BYTES = 10_000, 64 << 20
#: Bytes of rows of which one task may hold all, to train one of many configurations.
SIMULATED_BYTES = 512 << 20


def merge_on_driver(clients: int, width: int) -> bool:
    return clients <= DRIVER_CLIENTS and clients * width * 8 <= DRIVER_BYTES
