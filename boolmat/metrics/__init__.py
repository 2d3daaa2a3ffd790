"""Measures of space, work, time, memory and energy."""
