"""Uses of twins: audits, error checks, fine-tuning."""
