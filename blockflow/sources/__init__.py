"""Readers, carriers and writers."""
