"""Columns and vectorised kernels: draws, masks, divergences, warping distances."""
