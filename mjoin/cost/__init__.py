"""The time model of a job and its calibration."""
