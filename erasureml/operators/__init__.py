"""Distributed operators: encoding, partial gradients, stragglers, solvers and measures."""
