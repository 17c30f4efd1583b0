"""Routing of unbounded inputs."""
