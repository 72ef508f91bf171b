"""Pipelines, experiment workloads and their SQL counterparts."""
