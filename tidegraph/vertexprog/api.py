"""Vertex programs: what a user writes, and the programs supplied."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np


class Context:
    """What a vertex sees and does in one superstep."""

    __slots__ = ("superstep", "vertex", "outbox", "halted")

    def __init__(self, superstep: int):
        self.superstep, self.vertex, self.outbox, self.halted = superstep, None, [], False

    def send(self, dst, message) -> None:
        self.outbox.append((dst, message))

    def halt(self) -> None:
        self.halted = True


class VertexProgram:
    """State is JSON-free plain data of ``state_type``, messages are of ``message_type`` (Spark type strings).

    ``compute(ctx, vertex, state, messages, edges)`` returns the new state; ``edges`` are (target, weight) pairs. ``combine``
    merges two messages to one target, or is None.

    A program on numbers may also have a vector form, for runners that hold a part of the graph as arrays: ``vector_init(ids)``
    gives the states; ``vector_step(superstep, ids, state, received, degree)`` gives the new states, a value for each vertex
    and whether it sends it; ``vector_message(value, weight)`` makes the messages by plain arithmetic, of arrays or of columns. They combine by sum if ``identity`` is 0
    and by minimum if it is infinite; vertices without messages receive the identity.
    """

    state_type = "double"
    message_type = "double"
    combine: Callable | None = None
    max_supersteps = 10_000

    def vector_awake(self, superstep) -> bool:
        return False

    def init(self, vertex):
        return None

    def compute(self, ctx: Context, vertex, state, messages: list, edges: list):
        raise NotImplementedError


class ShortestPath(VertexProgram):
    state_type = message_type = "double"
    combine = staticmethod(min)

    def __init__(self, source, weighted: bool = False):
        self.source, self.weighted = source, weighted

    identity = math.inf

    def vector_init(self, ids):
        return np.full(len(ids), math.inf)

    def vector_step(self, superstep, ids, state, received, degree):
        if superstep == 0:
            received = np.where(ids == self.source, 0.0, math.inf)
        better = received < state
        state = np.minimum(state, received)
        return state, state, better

    def vector_message(self, value, weight):
        return value + (weight if self.weighted else 1.0)

    def compute(self, ctx, vertex, state, messages, edges):
        best = min(messages, default=None)
        if ctx.superstep == 0 and vertex == self.source:
            best = 0.0
        if best is not None and (state is None or best < state):
            state = best
            for dst, weight in edges:
                ctx.send(dst, state + (weight if self.weighted else 1.0))
        ctx.halt()
        return state


class Ranking(VertexProgram):
    """PageRank of ``rounds`` rounds over ``n`` vertices."""

    state_type = message_type = "double"
    combine = staticmethod(lambda a, b: a + b)

    def __init__(self, n: int, rounds: int = 10, damping: float = 0.85):
        self.n, self.rounds, self.damping = n, rounds, damping
        self.max_supersteps = rounds + 1

    identity = 0.0

    def vector_init(self, ids):
        return np.full(len(ids), 1.0 / max(self.n, 1))

    def vector_step(self, superstep, ids, state, received, degree):
        if superstep:
            state = (1 - self.damping) / self.n + self.damping * received
        return state, state / np.maximum(degree, 1), np.full(len(ids), superstep < self.rounds)

    def vector_message(self, value, weight):
        return value

    def vector_awake(self, superstep) -> bool:
        return superstep < self.rounds

    def init(self, vertex):
        return 1.0 / self.n

    def compute(self, ctx, vertex, state, messages, edges):
        if ctx.superstep:
            state = (1 - self.damping) / self.n + self.damping * sum(messages)
        if ctx.superstep < self.rounds:
            for dst, _ in edges:
                ctx.send(dst, state / len(edges))
        else:
            ctx.halt()
        return state


class Components(VertexProgram):
    """Smallest label along edges; run it on a symmetric graph for components. Labels are ids as doubles."""

    combine = staticmethod(min)
    identity = math.inf

    def vector_init(self, ids):
        return ids.astype(np.float64)

    def vector_step(self, superstep, ids, state, received, degree):
        better = (received < state) | (superstep == 0)
        state = np.minimum(state, received)
        return state, state, better

    def vector_message(self, value, weight):
        return value

    def init(self, vertex):
        return float(vertex)

    def compute(self, ctx, vertex, state, messages, edges):
        best = min(messages, default=state)
        if ctx.superstep == 0 or best < state:
            state = min(best, state)
            for dst, _ in edges:
                ctx.send(dst, state)
        ctx.halt()
        return state


class Factors(VertexProgram):
    """Collaborative filtering by gradient steps: every vertex of a bipartite rating graph sends its factors with the rating."""

    state_type = "array<double>"
    message_type = "array<double>"

    def __init__(self, rank: int = 8, rounds: int = 10, rate: float = 0.1, shrink: float = 0.05, seed: int = 5, centre: float = 0.0):
        self.rank, self.rounds, self.rate, self.shrink, self.seed, self.centre = rank, rounds, rate, shrink, seed, centre
        self.max_supersteps = rounds + 1

    def init(self, vertex):
        import random

        source = random.Random(f"{self.seed}:{vertex}")
        return [source.gauss(0, 0.1) for _ in range(self.rank)]

    def compute(self, ctx, vertex, state, messages, edges):
        if messages:
            moved = [0.0] * self.rank
            for rating, *other in messages:
                error = rating - self.centre - sum(a * b for a, b in zip(state, other))
                for i in range(self.rank):
                    moved[i] += error * other[i] - self.shrink * state[i]
            step = self.rate / max(1.0, len(messages) ** 0.5)
            state = [a + step * max(-50.0, min(50.0, m)) for a, m in zip(state, moved)]
        if ctx.superstep < self.rounds:
            for dst, rating in edges:
                ctx.send(dst, [rating, *state])
        else:
            ctx.halt()
        return state


class NeighbourOverlap(VertexProgram):
    """Strong overlap on an undirected graph: vertices send their neighbour lists, receivers count the smaller ids they meet.

    The state is a list of ``[other, common]`` of the others below the vertex with over ``threshold`` common neighbours.
    """

    state_type = "array<array<bigint>>"
    message_type = "array<bigint>"
    max_supersteps = 2

    def __init__(self, threshold: int):
        self.threshold = threshold

    def compute(self, ctx, vertex, state, messages, edges):
        if ctx.superstep == 0:
            near = sorted(dst for dst, _ in edges)
            for dst in near:
                ctx.send(dst, [x for x in near if x < dst])
            return []
        common: dict = {}
        for near in messages:
            for x in near:
                common[x] = common.get(x, 0) + 1
        ctx.halt()
        return [[x, n] for x, n in common.items() if n > self.threshold]


class NeighbourTies(VertexProgram):
    """Weak ties on an undirected graph: receivers of a neighbour list tell its sender how many of its ids they aren't joined to.

    The state is the number of unjoined pairs around the vertex. Every pair is told from both of its ends.
    """

    state_type = "bigint"
    message_type = "array<bigint>"
    max_supersteps = 3

    def compute(self, ctx, vertex, state, messages, edges):
        near = [dst for dst, _ in edges]
        if ctx.superstep == 0:
            for dst in near:
                ctx.send(dst, [vertex, *near])
            return 0
        if ctx.superstep == 1:
            own = {vertex, *near}
            for sender, *others in messages:
                ctx.send(sender, [sum(x not in own for x in others)])
            return 0
        ctx.halt()
        return sum(n for (n,) in messages) // 2
