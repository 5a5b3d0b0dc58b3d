"""Readers, writers and the views that the workloads run on."""
