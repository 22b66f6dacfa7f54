"""Operators on points, centres, edges and assignments."""
