"""Quality, agreement, profile and cost measures."""
