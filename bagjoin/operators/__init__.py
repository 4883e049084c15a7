"""Operators over factors: products, messages, projections, tries, inference."""
