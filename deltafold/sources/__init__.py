"""Readers, arrival rules, generators and sinks."""
