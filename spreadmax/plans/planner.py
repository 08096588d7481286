"""Which physical strategy finds the components of R simulations.

Lanes cost about 2 m R / B wide rows a round whatever the weights are; sparse
rows cost 2 p m R narrow rows a round; solving a simulation in one task costs
one shuffle but needs its sample in memory. A pilot of a few simulations, drawn
with the same hashes, measures p m.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import functions as F

from spreadmax.operators.graph import CascadeGraph

#: Bytes of a kept edge in a task that solves a simulation, and what such a task may hold.
EDGE_BYTES = 24
TASK_BYTES = 256 << 20
#: Memo rows that one wave of simulations may produce.
WAVE_ROWS = 4_000_000_000


@dataclass
class Plan:
    strategy: str
    width: int
    kept_per_sim: float
    waves: int


def fits_task(sampled, runs: int, task_bytes: int = TASK_BYTES) -> bool:
    """Whether one task holds any simulation of a stored sample (sim, src, dst), going by their mean number of edges."""
    return sampled.count() / max(1, runs) * EDGE_BYTES <= task_bytes


def choose(g: CascadeGraph, runs: int, width: int = 8, seed: int = 7, sampler: str = "xor", task_bytes: int = TASK_BYTES) -> Plan:
    from spreadmax.operators.sampling import fused_sample

    pilot = min(runs, 4)
    kept = fused_sample(g, pilot, seed, sampler).count() / pilot
    m = g.edges.agg(F.count(F.lit(1))).head()[0]
    waves = max(1, -(-int(2 * kept * runs) // WAVE_ROWS))
    if kept * EDGE_BYTES <= task_bytes:
        return Plan("local", width, kept, waves)
    if m and kept / m * width < 1.5:
        return Plan("star", width, kept, waves)
    return Plan("lanes", width, kept, waves)


def wave_of(plan: Plan, runs: int) -> int:
    """Simulations of a wave, so that none gives more than WAVE_ROWS rows."""
    return max(1, -(-runs // plan.waves))
