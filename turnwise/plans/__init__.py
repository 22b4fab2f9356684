"""Cost model, calibration, method choice, schedules and measures."""
