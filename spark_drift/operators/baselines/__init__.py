"""The detectors the component-wise degree is compared with."""
