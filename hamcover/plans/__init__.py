"""Parameters, label maps and closed-form costs. Everything here runs on the driver and is small."""
