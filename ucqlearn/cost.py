"""Closed forms of rounds, volume and work, and modelled communication time."""

from __future__ import annotations

import math

METHODS = ("vfl_sgd", "vfl_admm", "rel_sgd_v", "rel_admm_v", "rel_sgd", "rel_admm")

#: Latency in seconds, bandwidth in bits a second.
NETWORKS = {"us_uk": (0.136, 0.42e9), "us_us": (0.067, 1.15e9)}


def batches(n: int, batch: int) -> int:
    return max(1, math.ceil(n / batch))


def rounds(method: str, n: int, batch: int, inner: int = 10) -> int:
    """Communication rounds an epoch, outer and inner."""
    sgd = batches(n, batch)
    return {"vfl_sgd": sgd, "rel_sgd_v": sgd, "vfl_admm": 1, "rel_admm_v": 1, "rel_sgd": 2 * sgd, "rel_admm": 1 + inner}[method]


def volume(method: str, n: int, tables: int, classes: int = 1, alphas=(), used=(), parameters=(), shards=(), n_batches: int = 1, inner: int = 10, send_counts: str = "never") -> int:
    """Values sent an epoch, both ways. ``alphas``, ``used``, ``parameters`` and ``shards`` have a number for each table."""
    if method == "vfl_sgd":
        return 2 * tables * n * classes
    if method == "vfl_admm":
        return 3 * tables * n * classes
    if method in ("rel_sgd_v", "rel_sgd"):
        each = 2 * classes + (send_counts == "per_batch")
        total = each * sum(alphas)
        if method == "rel_sgd":
            total += 2 * sum(q * p for q, p in zip(shards, parameters) if q > 1) * n_batches
        return total
    total = 2 * classes * sum(used)
    if method == "rel_admm":
        total += inner * sum(3 * q * p for q, p in zip(shards, parameters) if q > 1)
    return total


def setup_volume(used, classes: int = 1, labels: int = 0, keys=()) -> int:
    """Values of the table mapping and the one-off fan-outs: ids, keys and labels up, counts down."""
    return sum(u * (1 + k) for u, k in zip(used, keys or [1] * len(used))) + labels * classes + sum(used)


def comm_time(n_rounds: int, n_bytes: int, network: str = "us_uk", latency_per: str = "round") -> float:
    latency, bits = NETWORKS[network]
    return (n_rounds if latency_per == "round" else 1) * latency + 8 * n_bytes / bits


def complexity(method: str, n: int, tables: int, batch: int, alphas, used, shards, inner: int = 10) -> dict:
    """Server rows, client rows (the busiest client), rounds and values an epoch in orders of growth, with real numbers."""
    k = batches(n, batch)
    q = sum(shards)
    server = {"vfl_sgd": n, "vfl_admm": n, "rel_sgd_v": n, "rel_admm_v": n, "rel_sgd": n + tables * k, "rel_admm": n + tables * inner}[method]
    client = {"vfl_sgd": n, "vfl_admm": n, "rel_sgd_v": max(alphas), "rel_admm_v": max(used), "rel_sgd": max(a / s for a, s in zip(alphas, shards)), "rel_admm": inner * max(u / s for u, s in zip(used, shards))}[method]
    sent = {"vfl_sgd": tables * n, "vfl_admm": tables * n, "rel_sgd_v": sum(alphas), "rel_admm_v": sum(used), "rel_sgd": sum(alphas) + q * k, "rel_admm": sum(used) + inner * q}[method]
    return {"method": method, "server_rows": float(server), "client_rows": float(client), "rounds": {"vfl_admm": 1, "rel_admm_v": 1, "rel_admm": inner}.get(method, k), "volume": float(sent)}
