"""Serializability verification of client-side transaction logs on Spark."""
