"""Operators: profiles, vectors, clusters, samples, types, annotations, measures."""
