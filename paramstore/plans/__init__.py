"""Pipelines that choose among operators."""
