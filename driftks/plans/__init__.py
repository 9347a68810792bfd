"""Planners: how an error budget becomes sketch and grid parameters, and the defaults."""
