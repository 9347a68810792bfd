"""Defaults and routing limits of the engine."""

ALPHA = 0.05
#: Precision of the distance when neither it nor a p-value precision is given.
PHI = 0.01
#: Most knots of a grid, in a plan and on the driver; beyond, the balanced split (which does not grow with N) is used and a warning given.
DRIVER_KNOTS = 200_000
#: Up to so many distinct values, the exact test on the value histogram is used when routing is automatic.
EXACT_DISTINCT = 100_000
#: Terms of the tail series, and the argument below which the tail is 1.
SERIES_TERMS = 100
TAIL_IS_ONE = 0.2
