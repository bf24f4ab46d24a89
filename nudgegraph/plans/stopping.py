"""How many samples are needed, and the greedy cover that the rule calls for."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nudgegraph.plans.planner import id_frame
from nudgegraph.session import Scratch

#: postings that the driver may hold for the greedy cover
LOCAL_POSTINGS = 4_000_000


def log_choose(n: int, k: int) -> float:
    return math.lgamma(n + 1) - math.lgamma(k + 1) - math.lgamma(n - k + 1)


def inflate_ell(ell: float, n: int) -> float:
    """A larger exponent, so that three bad events together stay below n^-ell."""
    return ell * (1 + math.log(3) / math.log(max(n, 2)))


def required_sketches(n: int, k: int, eps: float, ell: float, opt: float) -> int:
    """Samples with which greedy cover is within eps of its ratio, if the best value is ``opt``."""
    a = math.sqrt(ell * math.log(n) + math.log(2))
    b = math.sqrt((1 - 1 / math.e) * (log_choose(n, min(k, n)) + ell * math.log(n) + math.log(2)))
    return math.ceil(2 * n * ((1 - 1 / math.e) * a + b) ** 2 / (eps * eps * opt))


def trial_sketches(n: int, k: int, eps: float, ell: float, guess: float) -> int:
    """Samples that tell whether the best value reaches the guess."""
    e = math.sqrt(2) * eps
    rounds = max(math.log2(max(n, 4)), 2)
    return math.ceil((2 + 2 * e / 3) * (log_choose(n, min(k, n)) + ell * math.log(n) + math.log(rounds)) * n / (e * e * guess))


def _cover_arrays(sketch: np.ndarray, node: np.ndarray, k: int) -> list[tuple[int, int]]:
    """The greedy picks from postings as arrays; a posting is looked at again just once, when its sketch gets covered."""
    nodes, v = np.unique(node, return_inverse=True)
    sketches, s = np.unique(sketch, return_inverse=True)
    key = np.unique(s * max(1, len(nodes)) + v)
    s, v = key // max(1, len(nodes)), key % max(1, len(nodes))
    by_node = np.argsort(v, kind="stable")
    first_s, first_v = np.searchsorted(s, np.arange(len(sketches) + 1)), np.searchsorted(v[by_node], np.arange(len(nodes) + 1))
    count, open_, picks = np.bincount(v, minlength=len(nodes)), np.ones(len(sketches), bool), []
    while len(nodes) and len(picks) < k:
        best = int(count.argmax())  # the first of equals is the smallest id
        if not count[best]:
            break
        picks.append((int(nodes[best]), int(count[best])))
        mine = s[by_node[first_v[best] : first_v[best + 1]]]
        mine = mine[open_[mine]]
        open_[mine] = False
        size = first_s[mine + 1] - first_s[mine]
        gone = np.arange(size.sum()) + np.repeat(first_s[mine] - np.cumsum(size) + size, size)
        count -= np.bincount(v[gone], minlength=len(nodes))
    return picks


def cover_greedy(incidence: DataFrame, k: int, first: set[int] = frozenset(), unique: bool = False) -> list[tuple[int, int]]:
    """[(node, newly covered)]: each pick covers most sketches not covered yet, ties to the smallest id.

    ``incidence``: (sketch, node). While more than LOCAL_POSTINGS rows aren't
    covered, each pick is a partially aggregated count over them; what is left
    then comes to the driver. The two give the same picks. With ``unique`` no
    row occurs twice, so rows are counted where they are.
    """
    incidence = incidence.select("sketch", "node")
    if first:
        incidence = incidence.join(id_frame(incidence.sparkSession, first), "node", "left_anti")
    scratch = Scratch(incidence.sparkSession, "cover")
    picks, left = [], incidence
    while len(picks) < k and left.count() > LOCAL_POSTINGS:
        if not picks and not unique:
            left = scratch.keep(incidence.distinct(), "left")
        top = left.groupBy("node").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "node").first()
        picks.append((top.node, top.n))
        covered = left.where(F.col("node") == top.node).select("sketch")
        covered = F.broadcast(covered) if top.n <= LOCAL_POSTINGS // 4 else covered
        rest = scratch.keep(left.join(covered, "sketch", "left_anti"), "left")
        scratch.drop(left)
        left = rest
    if len(picks) < k:
        head = left.toArrow()
        picks += _cover_arrays(*(head.column(c).to_numpy() for c in ("sketch", "node")), k - len(picks))
    scratch.drop(*scratch.frames())
    return picks


@dataclass
class Sampled:
    """Sketches drawn so far and what is known about their number."""

    sketches: DataFrame
    theta: int
    lower: float
    certified: bool


def run_martingale(sample: Callable[[int, int], DataFrame], incidence: Callable[[DataFrame], DataFrame], keep: Callable[[DataFrame], DataFrame], n: int, k: int, eps: float, ell: float, most: int | None = None, fresh_final: bool = False) -> Sampled:
    """Samples until a lower bound of the best cover is certain, then the number that it calls for.

    ``sample(lo, hi)`` draws the sketches lo..hi-1, ``incidence`` has each (sketch, node) once. ``most``, if given, bounds
    the work; where it binds, the result isn't certified. With ``fresh_final`` the final
    sketches are all drawn anew, so that they don't depend on when sampling
    stopped.
    """
    done, drawn, lower = 0, None, 1.0
    most = math.inf if most is None else most

    def upto(theta: int) -> None:
        nonlocal done, drawn
        theta = min(theta, most)
        if theta > done:
            more = keep(sample(done, theta))
            drawn = more if drawn is None else drawn.unionByName(more)
            done = theta

    for i in range(1, max(2, math.ceil(math.log2(max(n, 4))))):
        guess = n / 2**i
        upto(trial_sketches(n, k, eps, ell, guess))
        value = n * sum(c for _, c in cover_greedy(incidence(drawn), k, unique=True)) / done
        if value >= (1 + math.sqrt(2) * eps) * guess:
            lower = value / (1 + math.sqrt(2) * eps)
            break
        if done >= most:
            lower = max(1.0, value / (1 + math.sqrt(2) * eps))
            break
    need = required_sketches(n, k, eps, ell, lower)
    if fresh_final:
        theta = min(need, most)
        return Sampled(keep(sample(done, done + theta)), theta, lower, need <= theta)
    upto(need)
    return Sampled(drawn, done, lower, need <= done)


def run_doubling(sample, incidence, keep, n: int, k: int, eps: float, ell: float, most: int | None = None) -> Sampled:
    """Doubles two independent halves until the second confirms the first one's picks."""
    theta = max(64, trial_sketches(n, k, eps, ell, n / 2))
    most = 1 << 40 if most is None else most
    while True:
        theta = min(theta, most // 2)
        a, b = keep(sample(0, theta)), keep(sample(most, most + theta))
        picks = cover_greedy(incidence(a), k, unique=True)
        claimed = n * sum(c for _, c in picks) / theta
        nodes = [v for v, _ in picks]
        drawn = incidence(b)
        hit = drawn.join(id_frame(drawn.sparkSession, nodes), "node", "left_semi").select("sketch").distinct().count()
        seen = n * hit / theta
        if hit >= 1 + (2 + 2 * eps / 3) * math.log(2 * max(n, 2) ** ell) / (eps * eps) and claimed <= (1 + eps) * seen or 2 * theta >= most:
            return Sampled(a, theta, max(1.0, seen / (1 + eps)), 2 * theta < most)
        theta *= 2
