"""Typed failures of the factorizations."""


class FactorizationError(ValueError):
    """A matrix or a call that cannot be factored."""


class GramNotPositiveDefinite(FactorizationError):
    """The Gram matrix has no Cholesky factor: the columns are (numerically) dependent."""


class RankDeficient(FactorizationError):
    """R has a diagonal entry that is zero to working accuracy, so it cannot be inverted."""


class TooFewRows(FactorizationError):
    """The matrix has fewer rows than columns."""


class BadRow(FactorizationError):
    """A row holds a null, a NaN, an infinity or the wrong number of values."""
