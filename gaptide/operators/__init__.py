"""Layouts, gaps, selection, solvers, trainers, measures."""
