"""Semirings, block kernels, schedules and placements."""
