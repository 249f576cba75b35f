"""Step sizes of the gradient methods."""


def inverse_time(eta0: float, t: int) -> float:
    """2 eta0 / (1 + t) for iteration t, counted from 1."""
    return 2 * eta0 / (1 + t)
