"""Files shared by the driver and the executors: intermediate tables, size-checked broadcasts."""

from ..storage import BROADCAST_ROWS, modest_batches, release, shared_folder, small, spill, table, width

__all__ = ["BROADCAST_ROWS", "modest_batches", "release", "shared_folder", "small", "spill", "table", "width"]
