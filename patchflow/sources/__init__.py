"""Adapters from the given tables to the engine's inputs."""
