"""Second review, pipeline: what a stage freed on the driver goes back to the system."""

import psutil
import pyarrow as pa

from longweave.llm.common import give_back


def test_freed_memory_goes_back():
    held = [bytearray(60_000) for _ in range(3000)]  # small pieces: the allocator keeps them
    mark = bytearray(1000)
    table = pa.array(range(3_000_000))
    del held, table
    give_back()
    assert pa.total_allocated_bytes() == 0 and psutil.Process().memory_info().rss < 600e6 and mark is not None
