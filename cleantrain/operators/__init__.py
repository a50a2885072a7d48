"""Gradients, solvers, sampling designs, estimators, detectors, cleaners, corruption and measures as DataFrame operators."""
