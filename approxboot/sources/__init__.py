"""Readers that sample before they load, and layouts that make sampling a partition filter."""
