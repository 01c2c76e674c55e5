"""Queries by area; importing this package registers them all."""

from treepack.queries import ans, baselines, cascade, catalogue, codebook, codec, functions, measures, sources, streams

ALL = (ans, baselines, cascade, catalogue, codebook, codec, functions, measures, sources, streams)
