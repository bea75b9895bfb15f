"""Schemes: who computes what, when a message leaves, and which arrivals end a round.

Every scheme is a table of messages and one recovery rule: within each cluster, the
``need``-th smallest first arrival over distinct codes; the round ends with the slowest
cluster.  Schemes that count messages give every message a code of its own; schemes that
need distinct codes let several messages carry the same one.  A hybrid cluster also ends
when one of its workers has sent the plain average of all it holds.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from typing import NamedTuple

CODED = ("gradcode_single", "gradcode_repeat", "gradcode_shared", "gradcode_layered", "gradcode_hybrid", "lagrange_single", "lagrange_multi")
UNCODED = ("wait_all", "uncoded_multi", "uncoded_partial", "uncoded_single", "first_workers", "backup_workers", "relaunch")


class Message(NamedTuple):
    worker: int
    step: int
    code: int
    cluster: int
    needs: int
    full: bool = False  # alone enough for its cluster
    first: bool = True  # of the rows of one message, the one that counts as traffic


@dataclass(frozen=True)
class Scheme:
    name: str
    K: int
    r: int = 1
    P: int = 1
    orders: tuple[int, ...] = ()
    order: int = 0
    polys: int = 1
    tolerance: float | Callable[[int], float] = 0.0
    need: int = 0
    extra: int = 0
    at_us: int = 0
    length_split: int = 1  # reserved: shortened coded gradients are only mentioned by the reference

    @property
    def label(self) -> str:
        tail = f"_{self.polys}" if self.name == "lagrange_multi" and self.polys > 1 else ""
        return self.name + tail

    @property
    def size(self) -> int:
        """Workers of a cluster."""
        return self.K // self.P

    @property
    def workers(self) -> int:
        return self.K + self.extra

    def at_round(self, t: int) -> Scheme:
        """The scheme of round ``t`` when the tolerance changes over time."""
        return replace(self, tolerance=self.tolerance(t)) if callable(self.tolerance) else self


def scheme(name: str, K: int, r: int = 1, **options) -> Scheme:
    """A checked scheme; raises ``ValueError`` where it cannot recover the gradient."""
    s = Scheme(name, K, r, **options)
    if name == "gradcode_repeat":
        if K % r:
            raise ValueError("repetition needs r to divide K")
        s = replace(s, P=K // r)
    if name not in CODED + UNCODED:
        raise ValueError(f"unknown scheme {name}")
    if s.length_split != 1:
        raise ValueError("shortened coded gradients are not implemented")
    if K < 1 or not 1 <= r <= K or K % s.P:
        raise ValueError("need 1 <= r <= K and P dividing K")
    if s.P > 1 and name.startswith("gradcode") and r > s.size:
        raise ValueError("clusters must be at least as large as r")
    if name == "gradcode_shared" and not 1 <= s.order <= r:
        raise ValueError("order must lie in 1..r")
    if name in ("gradcode_layered", "gradcode_hybrid") and (not s.orders or max(s.orders) > r or min(s.orders) < 1 or sum(s.orders) > s.size * len(s.orders)):
        raise ValueError("orders must lie in 1..r and sum to at most cluster size times their number")
    if name == "gradcode_hybrid" and r != s.size:
        raise ValueError("the plain average completes a cluster only if it holds all of it: r = K / P")
    if name == "lagrange_multi" and r % s.polys:
        raise ValueError("polys must divide r")
    if name in ("first_workers",) and not 1 <= s.need <= K:
        raise ValueError("need must lie in 1..K")
    if not feasible(s):
        raise ValueError(f"{name}: {available(s)} messages can never reach the threshold {message_threshold(s)}")
    return s


def tolerated(s: Scheme) -> int:
    share = s.tolerance(0) if callable(s.tolerance) else s.tolerance
    return int(share * s.K + 1e-9)


def message_threshold(s: Scheme) -> int:
    """Distinct codes that end a cluster (the whole round where there is one cluster)."""
    return {
        "wait_all": s.K,
        "gradcode_single": s.size - s.r + 1,
        "gradcode_repeat": 1,
        "gradcode_shared": s.size - s.order + 1,
        "gradcode_layered": s.size * len(s.orders) - sum(s.orders) + 1,
        "gradcode_hybrid": s.size * len(s.orders) - sum(s.orders) + 1,
        "lagrange_single": 2 * -(-s.K // s.r) - 1,
        "lagrange_multi": 2 * -(-s.K // s.polys) - 1,
        "uncoded_multi": s.K,
        "uncoded_partial": s.K - tolerated(s),
        "uncoded_single": s.K,
        "first_workers": s.need,
        "backup_workers": s.K,
        "relaunch": s.K,
    }[s.name]


def worker_threshold(s: Scheme) -> int:
    """Fewest complete workers that suffice whichever they are (the worst case).

    The worst set has every worker of all clusters but one, and as many of that one as still fall short: neighbours
    in the cyclic order, whose codes overlap the most.
    """
    need, size = message_threshold(s), s.size
    if s.name == "backup_workers":
        return s.workers - s.workers // s.K + 1  # all that lack the batch with the fewest holders
    if s.name in ("uncoded_multi", "uncoded_partial", "uncoded_single"):
        short = need - s.r  # c neighbours hold c + r - 1 batches
    elif s.name == "gradcode_shared":
        short = need - (s.r - s.order + 1)
    elif s.name == "gradcode_hybrid":
        short = 0  # one worker's plain average ends its cluster
    else:  # every message has a code of its own
        each = {"gradcode_layered": len(s.orders), "lagrange_multi": s.r // s.polys}.get(s.name, 1)
        short = -(-need // each) - 1
    return s.workers - (s.K if s.P == 1 else size) + max(0, short) + 1


def available(s: Scheme) -> int:
    found: dict[int, set[int]] = {}
    for m in messages(s):
        found.setdefault(m.cluster, set()).add(m.code)
    return min(len(c) for c in found.values())


def feasible(s: Scheme) -> bool:
    return available(s) >= message_threshold(s)


def recoverable(s: Scheme, workers) -> bool:
    """Whether these workers, each with all its messages, give the whole gradient."""
    held, codes, ended = set(workers), {c: set() for c in range(s.P)}, set()
    for m in messages(s):
        if m.worker in held:
            codes[m.cluster].add(m.code)
            if m.full:
                ended.add(m.cluster)
    need = message_threshold(s)
    return all(len(codes[c]) >= need or c in ended for c in codes)


def slots(s: Scheme) -> list[tuple[int, int, int]]:
    """(worker, position, batch): the cyclic order inside each cluster."""
    if s.name == "backup_workers":
        return [(w, 0, w % s.K) for w in range(s.workers)]
    size = s.size
    return [(w, j, w // size * size + (w % size + j) % size) for w in range(s.K) for j in range(s.r)]


def messages(s: Scheme) -> list[Message]:
    size, out = s.size, []
    for w in range(s.workers):
        c, i = w // size if s.name != "backup_workers" else 0, w % size
        if s.name in ("wait_all", "first_workers", "relaunch", "backup_workers"):
            out.append(Message(w, 0, w % s.K, 0, 1))
        elif s.name in ("gradcode_single", "gradcode_repeat", "lagrange_single"):
            out.append(Message(w, 0, w, c, s.r))
        elif s.name == "gradcode_shared":
            out += [Message(w, q, c * size + (i + q) % size, c, s.order + q) for q in range(s.r - s.order + 1)]
        elif s.name in ("gradcode_layered", "gradcode_hybrid"):
            for a, m in enumerate(sorted(s.orders)):
                out.append(Message(w, a, w * len(s.orders) + a, c, m))
            if s.name == "gradcode_hybrid":
                out.append(Message(w, len(s.orders), s.workers * len(s.orders) + w, c, s.r, full=True, first=max(s.orders) < s.r))
        elif s.name == "lagrange_multi":
            each = s.r // s.polys
            out += [Message(w, u, w * each + u, 0, (u + 1) * s.polys) for u in range(each)]
        elif s.name in ("uncoded_multi", "uncoded_partial"):
            out += [Message(w, u, (w + u) % s.K, 0, u + 1) for u in range(s.r)]
        elif s.name == "uncoded_single":
            out += [Message(w, 0, (w + u) % s.K, 0, s.r, first=u == 0) for u in range(s.r)]
    return out


def computation_load(s: Scheme) -> int:
    return s.r


def decode_ops(s: Scheme, d: int) -> dict[str, int]:
    """Operations of one decoding: sums over received codes, and building the weights."""
    n = message_threshold(s)
    if s.name.startswith("lagrange"):
        blocks = -(-s.K // (s.polys if s.name == "lagrange_multi" else s.r))
        return {"combine": n * d, "weights": n * n + blocks * n}
    if s.name.startswith("gradcode") and s.name != "gradcode_repeat":
        return {"combine": s.P * n * d, "weights": s.P * n * n}
    return {"combine": message_threshold(s) * s.P * d, "weights": 0}


def advise(measured: list[tuple[str, float, float]], cost_per_message: float) -> str:
    """The scheme of least expected time plus priced traffic among (name, time, load)."""
    return min(measured, key=lambda m: (m[1] + cost_per_message * m[2], m[0]))[0]


def expansion(s: Scheme, source_bytes: int, allow_expand: bool = False) -> int:
    """Bytes that coded copies of the data take; Lagrange codes store r times the source and must be asked for."""
    if not s.name.startswith("lagrange"):
        return 0
    if not allow_expand:
        raise ValueError("Lagrange codes store r coded copies of the data; pass allow_expand=True")
    return s.r * source_bytes
