"""Structural operators, block formats and cost measures of sparse matrices."""
