"""Noise planning, privacy accounting and schedules."""
