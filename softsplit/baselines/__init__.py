"""Systems that soft-split boosting is compared with."""
