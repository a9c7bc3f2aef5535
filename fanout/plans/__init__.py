"""Registered queries, experiment workloads and their SQL counterparts."""
