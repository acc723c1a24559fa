"""Techniques that the protocols are compared with or build on."""
