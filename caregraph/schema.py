"""Schemas that operators share."""

from __future__ import annotations

EVENT = (
    "event_id string, patient_id bigint, kind string, entity_id string, begin_ts timestamp_ntz, end_ts timestamp_ntz, "
    "time_kind string, stay_id string, situation string, result double, prompt string"
)
ENTITY = "entity_id string, kind string, label string, brand string, type string"
TRIPLE = "s string, p string, o string, o_kind string, datatype string, lang string"
RELATION = "patient_id bigint, src string, dst string, relation string, step int, origin string"

EVENT_KINDS = ("stay", "diagnosis", "drug", "assay", "surgery")
RELATIONS = ("Before", "After", "Concurrent", "During", "Overlap")
