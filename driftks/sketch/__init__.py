"""Mergeable rank-bound and KLL sketches and the tests that run on them."""
