"""Objectives and SQL functions."""
