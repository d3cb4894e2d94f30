"""Types of the media data model. All time is source time in whole milliseconds; intervals are half-open."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

MEDIA_REF = "struct<source_id:bigint,uri:string,duration_ms:bigint,clip_start_ms:bigint,clip_end_ms:bigint>"
UTTERANCE = "struct<start_ms:bigint,end_ms:bigint,speaker:string,text:string>"
EVENT = "struct<start_ms:bigint,end_ms:bigint,conf:double,evidence:string>"
CANDIDATE = "struct<start_ms:bigint,end_ms:bigint,score:double>"
DETECTION = "struct<det_id:bigint,frame_no:int,ts_ms:bigint,cls:string,x:double,y:double,w:double,h:double,conf:double,emb:array<double>>"
TRACK = (
    "struct<track_id:bigint,start_ms:bigint,end_ms:bigint,first_x:double,first_y:double,last_x:double,last_y:double,"
    "vx:double,vy:double,n_det:int,cls:string,emb:array<double>>"
)
ASSOCIATION = "struct<vehicle_id:string,attributes:map<string,string>,timeline:array<struct<source_id:bigint,start_ms:bigint,end_ms:bigint>>,match_score:double>"

GRANULARITIES = ("video", "clip", "frame", "detection", "track")


def media_ref(source_id: Column, duration_ms: Column, uri: Column | None = None) -> Column:
    """A whole source as a media value: a reference, never bytes."""
    uri = F.concat(F.lit("source:"), source_id.cast("string")) if uri is None else uri
    duration = duration_ms.cast("bigint")
    return F.struct(
        source_id.cast("bigint").alias("source_id"), uri.alias("uri"), duration.alias("duration_ms"), F.lit(0).cast("bigint").alias("clip_start_ms"), duration.alias("clip_end_ms")
    )


def clock(ms: Column) -> Column:
    """Source time as ``h:mm:ss.mmm``."""
    return F.format_string("%d:%02d:%02d.%03d", F.floor(ms / 3_600_000), F.floor(ms / 60_000) % 60, F.floor(ms / 1000) % 60, ms % 1000)
