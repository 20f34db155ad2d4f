"""Kernels on block arrays and small graphs; they run on the driver or inside one task."""
