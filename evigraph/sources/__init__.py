"""Source tables to capsules."""
