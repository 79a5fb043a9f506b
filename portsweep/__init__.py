"""Bounded-memory graph protocols as DataFrame programs."""
