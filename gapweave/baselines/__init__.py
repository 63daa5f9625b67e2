"""Strategies that the framework is compared with."""
