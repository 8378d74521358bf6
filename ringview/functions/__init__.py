"""Payload rings and lifting functions."""
