"""Switch rules, tuning and published figures."""
