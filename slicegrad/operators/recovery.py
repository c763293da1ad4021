"""Coarse recovery, the contrast to rerunning one task: go back to the last snapshot."""

from __future__ import annotations

from slicegrad.operators.kernel import train_net
from slicegrad.operators.train import TrainResult


def train_with_snapshots(samples, net, optim, rounds: int, every: int, fails_at: set[int] = frozenset(), **options) -> tuple[TrainResult, int]:
    """The result, and how many rounds were run again. A failure loses all rounds since the last snapshot."""
    snapshot: TrainResult | None = None
    done = lost = 0
    pending = set(fails_at)
    while done < rounds:
        step = min(every, rounds - done)
        hit = [k for k in sorted(pending) if done < k <= done + step]
        if hit:
            pending.discard(hit[0])
            lost += hit[0] - done
            train_net(samples, net, optim, hit[0] - done, init=snapshot, **options)  # the work that is lost
            continue
        snapshot = train_net(samples, net, optim, step, init=snapshot, **options)
        done += step
    return snapshot, lost
