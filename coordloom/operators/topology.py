"""Machine topology, bucket size and placement of threads."""

from __future__ import annotations

import glob
import os
from dataclasses import dataclass

ENTRY_BYTES = 8


@dataclass(frozen=True)
class Topology:
    nodes: int
    cores: int  # physical cores of a node
    line_bytes: int = 64
    llc_bytes: int = 32 << 20


#: The two machines of the evaluation. Their numbers of nodes and the first one's cores. Line and cache sizes
#: and the second one's cores aren't stated; they are our assumptions.
MACHINES = {"X": Topology(4, 8, 64, 16 << 20), "P": Topology(2, 20, 128, 10 << 20)}


def _read(path: str, default: int) -> int:
    try:
        with open(path) as f:
            text = f.read().strip()
        return int(text[:-1]) << {"K": 10, "M": 20}[text[-1]] if text[-1:] in "KM" else int(text)
    except (OSError, ValueError, KeyError):
        return default


def detect() -> Topology:
    """From sysfs, with defaults where it says nothing."""
    cache = "/sys/devices/system/cpu/cpu0/cache/index3/"
    nodes = max(1, len(glob.glob("/sys/devices/system/node/node[0-9]*")))
    cores = {(_read(f"{p}/physical_package_id", 0), _read(f"{p}/core_id", k)) for k, p in enumerate(sorted(glob.glob("/sys/devices/system/cpu/cpu[0-9]*/topology")))}
    return Topology(nodes, max(1, (len(cores) or os.cpu_count() or 1) // nodes), _read(cache + "coherency_line_size", 64), _read(cache + "size", 32 << 20))


def bucket_size(topology: Topology) -> int:
    """Model entries of a cache line."""
    return max(1, topology.line_bytes // ENTRY_BYTES)


def choose_bucket(n: int, topology: Topology, cutoff: int | None = None) -> int:
    """Buckets only where the model (n entries) doesn't fit in the last-level cache, or exceeds ``cutoff`` entries."""
    too_large = n > cutoff if cutoff is not None else ENTRY_BYTES * n > topology.llc_bytes
    return bucket_size(topology) if too_large else 1


def plan_placement(threads: int, topology: Topology, data_node: int = 0) -> list[tuple[int, int]]:
    """(node, threads): one node if its cores suffice, else an even split over the fewest nodes; the data's node always first."""
    if threads <= topology.cores:
        return [(data_node, threads)]
    if threads > topology.nodes * topology.cores:
        raise ValueError("more threads than physical cores")
    used = -(-threads // topology.cores)
    nodes = [data_node, *[k for k in range(topology.nodes) if k != data_node]][:used]
    return [(node, threads // used + (r < threads % used)) for r, node in enumerate(nodes)]


def preferred_hosts(df) -> list[str]:
    """Hosts that hold the input's blocks, as Spark's scheduler sees them."""
    rdd = df._jdf.queryExecution().toRdd()
    hosts = set()
    for part in rdd.partitions():
        seq = rdd.preferredLocations(part)
        hosts |= {seq.apply(k) for k in range(seq.size())}
    return sorted(hosts)
