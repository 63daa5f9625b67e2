"""Imputation learners behind one protocol."""
