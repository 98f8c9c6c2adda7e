"""Which direction a step takes."""

from __future__ import annotations

from dataclasses import dataclass

ALPHA, BETA = 64, 8


@dataclass(frozen=True)
class StepState:
    frontier_vertices: int
    frontier_edges: int
    unexplored_edges: int
    previous_vertices: int
    vertices: int


def choose(now: str, left_bottom_up: bool, s: StepState, alpha: float = ALPHA, beta: float = BETA, guard: bool = True) -> str:
    """``top_down`` or ``bottom_up`` for the next step.

    Bottom-up starts when the frontier's edges outweigh 1/alpha of the unexplored ones while the
    frontier grows, ends when the frontier falls below 1/beta of the vertices, and with ``guard``
    never starts a second time.
    """
    if now == "bottom_up":
        return "top_down" if s.frontier_vertices * beta < s.vertices else "bottom_up"
    if guard and (left_bottom_up or s.frontier_vertices <= s.previous_vertices):
        return "top_down"
    return "bottom_up" if s.frontier_edges * alpha > s.unexplored_edges else "top_down"
