"""Operators on sequences: histograms, shortlists, periodicity, quantiser, relational operators."""
