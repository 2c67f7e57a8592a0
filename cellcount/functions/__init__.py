"""Scales, quantizers and aggregate states."""
