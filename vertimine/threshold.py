"""Minimum support: a count, or a fraction of the number of transactions resolved in decimal arithmetic."""

from decimal import ROUND_CEILING, Decimal


def resolve(n_transactions: int, min_support: float | str | Decimal | None = None, min_count: int | None = None) -> int:
    """ceil(fraction * n); 0.1 means one tenth exactly. A count is taken as it is. Never below 1."""
    if (min_support is None) == (min_count is None):
        raise ValueError("give either min_support or min_count")
    if min_count is not None:
        if int(min_count) != min_count or min_count < 1:
            raise ValueError(f"min_count must be a whole number of at least 1, not {min_count}")
        return int(min_count)
    fraction = Decimal(str(min_support))
    if not 0 < fraction <= 1:
        raise ValueError(f"min_support must be above 0 and at most 1, not {min_support}")
    return max(1, int((fraction * n_transactions).to_integral_value(ROUND_CEILING)))
