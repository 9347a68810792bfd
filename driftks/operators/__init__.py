"""Methods over DataFrames: samples, quantiles, distribution functions, tests and reports."""
