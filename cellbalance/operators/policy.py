"""When to run the pipeline."""

from __future__ import annotations


def every(n: int):
    """Each n-th step."""
    return lambda step, **_: step % n == 0


def threshold(tau: float):
    """Only when the largest load passes tau times the mean."""
    return lambda step, max_load, mean_load, **_: max_load > tau * mean_load


def amortized(pipeline_seconds: float, seconds_per_load: float):
    """Only when the time saved over the steps left pays for the run."""
    return lambda step, max_load, mean_load, steps_left, **_: (max_load - mean_load) * seconds_per_load * steps_left > pipeline_seconds


def both(*due):
    """Only when all of the triggers fire."""

    def fires(step, **state):
        out = True
        for one in due:
            out = out & one(step, **state)
        return out

    return fires
