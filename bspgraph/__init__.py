"""Vertex programs as bulk-synchronous DataFrame supersteps."""
