"""A model of communication time. Bytes are measured from containers; bandwidth and time are modelled."""

from __future__ import annotations


def comm_bytes(kind: str, workers: int, size: float) -> float:
    """Bytes that each worker moves: ring all-reduce, all-gather, or to and from a parameter server."""
    if kind == "allreduce":
        return 2 * (workers - 1) / workers * size
    if kind == "allgather":
        return (workers - 1) * size
    if kind == "ps":
        return 2 * size
    raise ValueError(kind)


def iteration_time(compute_s: float, codec_s: float, kind: str, workers: int, size: float, bits_per_s: float) -> dict[str, float]:
    comm = 8 * comm_bytes(kind, workers, size) / bits_per_s
    return {"compute": compute_s, "codec": codec_s, "comm": comm, "total": compute_s + codec_s + comm}
