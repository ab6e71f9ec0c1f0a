"""Measures, simulation, training and tuners."""
