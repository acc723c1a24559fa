"""Part of the synchronisation engine."""
