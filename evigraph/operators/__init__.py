"""Operators over capsules: structure, status, tags and links, packs, trust, clearance, search."""
