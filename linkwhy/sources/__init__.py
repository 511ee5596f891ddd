"""Readers, knowledge graph profiles and the store."""
