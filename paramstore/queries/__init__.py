"""Registered queries over the given tables, by chapter; importing this package fills paramstore.registry."""

from paramstore.queries import accuracy, codecs, duplication, parameters, pipeline, profile, relational, streams  # noqa: F401
